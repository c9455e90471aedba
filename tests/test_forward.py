"""Forward queries by rings against all pairs; results of all stops and routes at once against reverse queries."""

import random

import pytest
from pyspark.sql import functions as F

from transitlens.operators import knn
from transitlens.operators.planner import vertex_omega
from transitlens.operators.reverse import reverse_routes
from transitlens.plans.layout import build_endpoint_index, build_stop_index
from transitlens.plans.workloads import route_queries
from transitlens.schema import ENDPOINTS, ROUTE_POINTS

draw = random.Random(8)
PLACES = [(draw.randrange(0, 20) * 700, draw.randrange(0, 20) * 700) for _ in range(40)]
ROUTES = [(r, i, x * 100_000 + y, x, y) for r in range(1, 10) for i, (x, y) in enumerate(draw.sample(PLACES, 6), 1)]
#: Some endpoints far from every route, one on a stop, one repeated.
POINTS = [(t, s, draw.randrange(-3000, 18000), draw.randrange(-3000, 18000)) for t in range(60) for s in "od"]
POINTS += [(90, "o", 300_000, 0), (90, "d", 5_000_000, 7), (91, "o", *PLACES[0]), (92, "d", 5, 5), (92, "d", 5, 5)]


@pytest.fixture(scope="module")
def tables(spark):
    routes = spark.createDataFrame(ROUTES, ROUTE_POINTS)
    points = spark.createDataFrame([(*p, None) for p in POINTS], ENDPOINTS)
    return routes, points, build_stop_index(routes), build_endpoint_index(points)


@pytest.mark.parametrize("k", [1, 4, 9, 30])
def test_rings_equal_all_pairs(tables, k):
    routes, points, stops, _ = tables
    columns = ["transition_id", "side", "route_id", "d2"]
    want = {tuple(r) for r in knn.nearest_routes(points, routes, k).select(columns).collect()}
    assert {tuple(r) for r in knn.nearest_by_rings(points, stops, k).select(columns).collect()} == want
    assert {r.transition_id for r in knn.transition_routes(knn.nearest_by_rings(points, stops, k), "both").collect()} <= {r.transition_id for r in knn.transition_routes(knn.nearest_by_rings(points, stops, k)).collect()}


def test_row_ties_give_exactly_k(tables):
    routes, points, *_ = tables
    counts = knn.nearest_routes(points.distinct(), routes, 3, "row").groupBy("transition_id", "side").count()
    assert {r["count"] for r in counts.collect()} == {3}


def test_a_forward_pass_answers_the_reverse_queries_of_all_routes(tables):
    routes, points, stops, index = tables
    asked = route_queries(routes)
    forward = knn.transition_routes(knn.nearest_by_rings(points, stops, 3))
    want = {(r.route_id, r.transition_id, r["mask"]) for r in forward.collect()}
    assert {tuple(r) for r in reverse_routes(stops, index, asked, 3, method="split").collect()} == want
    assert {tuple(r) for r in reverse_routes(routes, points.distinct(), asked, 3, method="scan").collect()} == want


def test_results_of_all_stops(tables):
    _, _, stops, index = tables
    by_rings, by_queries = (vertex_omega(stops, index, (1, 3), method=m) for m in ("rings", "queries"))
    assert {tuple(r) for r in by_rings.collect()} == {tuple(r) for r in by_queries.collect()}
    only = stops.points().limit(2)
    assert vertex_omega(stops, index, (3,), only).select("stop_id").distinct().count() <= 2


def test_nothing_to_look_at(spark, tables):
    routes, points, stops, _ = tables
    assert knn.nearest_by_rings(points.limit(0), stops, 2).count() == 0
    assert knn.nearest_by_rings(points, build_stop_index(routes.limit(0)), 2).count() == 0
    with pytest.raises(ValueError):
        knn.transition_routes(points.withColumn("route_id", F.lit(1)), "all")
