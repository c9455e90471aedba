"""Forward passes by tiles: kernels against brute force, ends at several places, what is shuffled."""

import random
import uuid

import numpy as np
import pyarrow as pa

from transitlens.operators import knn, tiles
from transitlens.plans.layout import build_stop_index
from transitlens.plans.shared import shared_dir
from transitlens.schema import ENDPOINTS, ROUTE_POINTS
from transitlens.sources import fixtures


def test_kth_distances_of_a_tile_split_into_quarters(monkeypatch):
    monkeypatch.setattr(tiles, "BLOCK", 64)
    monkeypatch.setattr(tiles, "LISTED", 16)
    draw = random.Random(3)
    spots = [(draw.randrange(-200, 1224), draw.randrange(-200, 1224), sorted(draw.sample(range(30), draw.randint(1, 4)))) for _ in range(300)]
    stops = tiles.Stops(pa.table({"x_m": [s[0] for s in spots], "y_m": [s[1] for s in spots], "routes": pa.array([s[2] for s in spots], pa.list_(pa.int64()))}))
    x, y = (np.array([draw.randrange(1024) for _ in range(200)]) for _ in "xy")
    ks, got = (1, 5, 12), {}

    def solve(rows, near, d2, box, zone):
        kth = tiles.kth_of(d2, near, stops, ks)
        fine = (kth[:, -1] >= 0) & (kth.max(axis=1) < tiles.safe_sq(x[rows], y[rows], box, zone))
        got.update(zip(rows[fine].tolist(), kth[fine].tolist(), strict=True))
        return rows[~fine]

    tiles.quarters(x, y, stops, (0, 0, 1024), 200, solve)
    assert len(got) == 200
    for i, found in got.items():
        best = {}
        for sx, sy, routes in spots:
            for r in routes:
                best[r] = min(best.get(r, 1 << 60), int((x[i] - sx) ** 2 + (y[i] - sy) ** 2))
        assert found == [sorted(best.values())[k - 1] for k in ks]


def test_masks_of_ends_at_several_places_and_far_away(spark, monkeypatch):
    """However many stops there are, an end far from all of them is answered too."""
    monkeypatch.setattr(knn, "SCAN_STOPS", 3)
    draw = random.Random(4)
    rows = [(r, i, 100 * r + i, draw.randrange(9000), draw.randrange(9000)) for r in range(8) for i in range(4)]
    ends = [(t, s, draw.randrange(9000), draw.randrange(9000)) for t in (1, 2, 2, 3) for s in "od"] + [(4, "o", 30_000_000, 5), (4, "d", 1, 1)]
    points = spark.createDataFrame([(*e, None) for e in ends], ENDPOINTS)
    want = set()
    for k in (1, 3):
        for t in {e[0] for e in ends}:
            masks = {}
            for s, bit in (("o", 1), ("d", 2)):
                best = {r: min((e[2] - x) ** 2 + (e[3] - y) ** 2 for e in ends if e[:2] == (t, s) for q, _, _, x, y in rows if q == r) for r in range(8)}
                for r, v in best.items():
                    if sum(o < v for o in best.values()) < k:
                        masks[r] = masks.get(r, 0) | bit
            want |= {(k, t, r, m) for r, m in masks.items()}
    index = build_stop_index(spark.createDataFrame(rows, ROUTE_POINTS))
    found = knn.masks_by_rings(points, index, (1, 3))
    assert {tuple(r) for r in found.collect()} == want and found.count() == len(want)
    assert {tuple(r) for r in knn.masks_by_rings(points, index, (1, 3), "both").collect()} == {w for w in want if w[3] == 3}


def test_routes_take_one_shuffle_and_equal_their_sql(spark):
    folder = f"{shared_dir(spark)}/fixtures-{uuid.uuid4().hex}"
    draw = random.Random(5)
    rows = [(draw.randrange(40), draw.choice([None, 1, 2, 3]), draw.randrange(1, 8), draw.randrange(9), draw.choice([None, 3.0, 4.0, 7.0]), draw.random()) for _ in range(400)]
    spark.createDataFrame(rows, "l_orderkey long, l_suppkey long, l_linenumber int, l_partkey long, l_quantity double, l_extendedprice double").write.parquet(f"{folder}/lineitem.parquet")
    spark.range(9).withColumnRenamed("id", "p_partkey").write.parquet(f"{folder}/part.parquet")
    got = fixtures.route_points(spark, folder)
    want = fixtures._table(spark, folder, fixtures.route_points_sql("spark"), "lineitem", "part")
    assert got.schema.simpleString() == want.schema.simpleString()
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    assert got._jdf.queryExecution().optimizedPlan().toString().count("Window [") == 1


def test_lists_are_shuffled_and_not_pairs(spark):
    """No exchange of a forward pass carries a row for each endpoint and route."""
    rows = [(r, 1, 7, 100, 100) for r in range(50)]
    points = spark.createDataFrame([(t, s, 90 + t, 90, None) for t in range(20) for s in "od"], ENDPOINTS)
    plan = knn.masks_by_rings(points, build_stop_index(spark.createDataFrame(rows, ROUTE_POINTS)), (10,))
    assert plan.filter("mask = 3").count() == 20 * 50
    lines = plan._jdf.queryExecution().optimizedPlan().toString().splitlines()
    assert not [x for x in lines if ("Aggregate" in x or "Repartition" in x) and "route_id" in x]
