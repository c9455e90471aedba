"""The network: edges both ways, and what is shuffled for them."""

import time

from transitlens.operators import graph
from transitlens.schema import ROUTE_POINTS


def _shuffled(spark, df):
    """Rows that a run of ``df`` writes to shuffles."""
    store, sc = spark.sparkContext._jsc.sc().statusStore(), spark.sparkContext
    sc.setJobGroup("edges", "edges")
    df.write.format("noop").mode("overwrite").save()
    time.sleep(1)
    stages = {s for j in sc.statusTracker().getJobIdsForGroup("edges") for s in sc.statusTracker().getJobInfo(j).stageIds}
    sc.setLocalProperty("spark.jobGroup.id", None)
    return sum(store.lastStageAttempt(s).shuffleWriteRecords() for s in stages)


def test_edges_both_ways_from_segments_shuffled_once(spark):
    places = {1: (0, 0), 2: (300, 400), 3: (0, 1000), 4: (50, 60)}
    ways = [(1, 2, 3), (3, 2, 1), (2, 2, 4), (2, 1)]
    rows = [(r, i + 1, s, *places[s]) for r, way in enumerate(ways) for i, s in enumerate(way)]
    edges = graph.build(spark.createDataFrame(rows, ROUTE_POINTS))
    one = {(1, 2, 500), (2, 3, 671), (2, 4, 422)}
    assert {tuple(r) for r in edges.collect()} == one | {(b, a, n) for a, b, n in one}
    assert {tuple(r) for r in graph.build(spark.createDataFrame(rows, ROUTE_POINTS), directed=True).collect()} == {(1, 2, 500), (2, 1, 500), (2, 3, 671), (3, 2, 671), (2, 4, 422)}
    many = spark.createDataFrame([(r, i + 1, 10 * (r % 4) + i, 100 * i, 100 * (r % 4)) for r in range(400) for i in range(10)], ROUTE_POINTS).repartition(4, "route_id")
    # Points once, by route and for the window; edges of at most four tasks, at first one way.
    assert _shuffled(spark, graph.build(many)) < 4000 + 4 * 36 * 3
