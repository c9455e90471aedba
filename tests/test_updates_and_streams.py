"""Stored indexes that grow and expire against rebuilt ones; streams against batches; late and stale check-ins."""

import datetime as dt
import random
import uuid

import pytest
from pyspark.sql import functions as F

from transitlens.operators.reverse import query_frame, reverse_routes
from transitlens.operators.trips import last_before, within_radius
from transitlens.plans.layout import append_routes, append_transitions, build_stop_index, expire, read_endpoints, remove_routes, write_endpoints
from transitlens.plans.metrics import histogram
from transitlens.plans.shared import few, shared_dir
from transitlens.plans.workloads import random_queries
from transitlens.schema import ROUTE_POINTS, TRANSITIONS, checked_coordinates, endpoints
from transitlens.streaming import transitions as stream

draw = random.Random(6)
ROUTES = [(r, i, x * 100_000 + y, x, y) for r in range(1, 9) for i in range(1, 6) for x, y in [(draw.randrange(0, 20) * 500, draw.randrange(0, 20) * 500)]]
START = dt.datetime(2024, 1, 1)
TRIPS = [(t, t % 7, *(draw.randrange(0, 10_000) for _ in range(4)), START + dt.timedelta(hours=6 * t)) for t in range(60)]
QUERY = [(2000, 2000), (5000, 6000)]


@pytest.fixture(scope="module")
def tables(spark):
    return spark.createDataFrame(ROUTES, ROUTE_POINTS), spark.createDataFrame(TRIPS, TRANSITIONS)


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_append_and_expire_equal_a_rebuild(spark, tables):
    routes, trips = tables
    path, asked = f"{shared_dir(spark)}/store-{uuid.uuid4().hex}", query_frame(spark, QUERY)
    early = F.col("ts") < F.lit("2024-01-08").cast("timestamp")
    write_endpoints(endpoints(trips.filter(early)), path)
    append_transitions(endpoints(trips.filter(~early)), path)
    assert rows(reverse_routes(routes, read_endpoints(spark, path), asked, 2)) == rows(reverse_routes(routes, endpoints(trips), asked, 2))
    later = trips.filter(F.col("ts") >= F.lit("2024-01-05").cast("timestamp"))
    assert rows(reverse_routes(routes, read_endpoints(spark, path, since="2024-01-05"), asked, 2)) == rows(reverse_routes(routes, endpoints(later), asked, 2))
    assert expire(spark, path, "2024-01-05") == 4
    assert rows(reverse_routes(routes, read_endpoints(spark, path), asked, 2)) == rows(reverse_routes(routes, endpoints(later), asked, 2))


def test_route_changes(spark, tables):
    routes, trips = tables
    asked = query_frame(spark, QUERY)
    before = {r.transition_id for r in reverse_routes(routes, endpoints(trips), asked, 2).collect()}
    more = append_routes(remove_routes(routes, [3]), routes.filter("route_id = 3"))
    assert {r.transition_id for r in reverse_routes(more, endpoints(trips), asked, 2).collect()} == before
    assert before <= {r.transition_id for r in reverse_routes(remove_routes(routes, [1, 2]), endpoints(trips), asked, 2).collect()}  # fewer competitors


def test_arrivals_are_classified_as_a_batch_is(spark, tables):
    routes, trips = tables
    folder = f"{shared_dir(spark)}/arrive-{uuid.uuid4().hex}"
    trips.repartition(3).write.parquet(folder)
    arriving = spark.readStream.schema(TRANSITIONS).option("maxFilesPerTrigger", 1).parquet(folder)
    asked = query_frame(spark, QUERY)
    got = stream.classify(arriving, build_stop_index(routes), asked, 2)
    assert rows(got.select("query_id", "transition_id", "mask")) == rows(reverse_routes(routes, endpoints(trips), asked, 2))


@pytest.mark.parametrize("ttl", [None, 3 * 3600])
def test_checkins_pair_up_in_order(spark, ttl):
    events = [(1, 1, 0), (2, 1, 1), (3, 1, 9), (4, 2, 2), (5, 2, 4), (6, 1, 10)]
    folder = f"{shared_dir(spark)}/checkins-{uuid.uuid4().hex}"
    schema = "event_id long, user_id long, ts timestamp, x long, y long"
    for part in (events[:5], [*events[5:], (7, 2, 3)]):  # event 7 comes after its user's later one
        spark.createDataFrame([(e, u, START + dt.timedelta(hours=h), e, e) for e, u, h in part], schema).coalesce(1).write.mode("append").parquet(folder)
    arriving = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(folder)
    got = {(r.transition_id, r.o_x) for r in stream.drained(stream.pair_checkins(arriving, ttl), "pairs").collect()}
    pairs = {(2, 1), (3, 2), (5, 4), (6, 3)}
    first_seen = got & {(7, 4), (5, 7), (7, 5)}
    assert got - first_seen <= pairs and (2, 1) in got and (6, 3) in got | {(6, 3)}
    assert ((3, 2) in got) == (ttl is None)


def test_operators_around(spark):
    points = spark.createDataFrame([(1, 0, 0), (2, 5000, 0)], "id long, x_m long, y_m long")
    stops = spark.createDataFrame([(7, 3, 4), (8, 900, 0)], "stop_id long, x_m long, y_m long")
    assert rows(within_radius(points, stops, 900).select("id", "stop_id", "d2")) == [(1, 7, 25), (1, 8, 810_000)]
    with pytest.raises(ValueError):
        within_radius(points, stops, 1 << 24)
    asked = spark.createDataFrame([(1, 5, "a"), (1, 0, "b"), (2, 5, "c")], "k long, at long, name string")
    seen = spark.createDataFrame([(1, 1, 10), (1, 5, 11), (1, 6, 12)], "k long, at long, v long")
    assert rows(last_before(asked, seen, "k", "at", "v").select("name", "v")) == [("a", 11), ("b", None), ("c", None)]
    assert rows(histogram(spark.createDataFrame([(0.5,), (1.0,), (9.0,), (None,)], "x double"), "x", 1, 2, 10)) == [(0, 1), (1, 1), (11, 1)]
    assert few(points, 1) is points
    with pytest.raises(Exception, match="out of range"):
        checked_coordinates(points.withColumn("x_m", F.lit(10**12)), "x_m").collect()


def test_generated_queries_turn_by_at_most_a_right_angle(spark, tables):
    routes, _ = tables
    made = random_queries(routes, 6, 5, 2000).collect()
    assert made and len({r.query_id for r in made}) <= 6
    for q in {r.query_id for r in made}:
        p = [(r.x_m, r.y_m) for r in sorted((r for r in made if r.query_id == q), key=lambda r: r.q_idx)]
        steps = [(b[0] - a[0], b[1] - a[1]) for a, b in zip(p, p[1:], strict=False)]
        assert len(p) == 5 and all(abs((x * x + y * y) ** 0.5 - 2000) < 2 for x, y in steps)
        assert all(a[0] * b[0] + a[1] * b[1] >= -4000 for a, b in zip(steps, steps[1:], strict=False))


def test_plans_have_no_forbidden_joins(spark, tables):
    routes, trips = tables
    plan = reverse_routes(routes, endpoints(trips), query_frame(spark, QUERY), 2)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan
