"""Queries of one point each: filtered, pruned and counted in tiles, with what the tiles leave open by the descent."""

import random

from transitlens.operators import lone, planner, verify
from transitlens.operators.planner import Network, Points, all_paths, best_by_enumeration, paths_within, served
from transitlens.operators.pruning import prune_endpoints
from transitlens.operators.reverse import filtered_probes
from transitlens.plans.layout import build_endpoint_index, build_stop_index
from transitlens.schema import ROUTE_POINTS

ENDPOINTS = "transition_id long, side string, x_m long, y_m long"


def plane(spark, draw):
    """A town of close stops, a few far away, and endpoints in and around it, some of them on stops."""
    places = [(draw.randint(0, 12_000), draw.randint(0, 12_000)) for _ in range(250)] + [(40_000, 41_000), (90_000, -20_000), (-30_000, 70_000)]
    routes = [(r, seq + 1, at, *places[at]) for r in range(40) for seq, at in enumerate(draw.sample(range(len(places)), 12))]
    ends = [(t, side, *(draw.choice(places) if t % 9 == 0 else (draw.randint(-6_000, 18_000), draw.randint(-6_000, 18_000)))) for t in range(150) for side in "od"]
    ends += [(900, "o", 60_000, 60_000), (901, "d", 85_000, -15_000)]
    return routes, ends


def brute(routes, ends, k):
    stops = {r[2]: r[3:] for r in routes}
    out = set()
    for t, side, x, y in ends:
        nearest = {}
        for r, _, _, sx, sy in routes:
            nearest[r] = min(nearest.get(r, 1 << 60), (x - sx) ** 2 + (y - sy) ** 2)
        for s, (sx, sy) in stops.items():
            dq = (x - sx) ** 2 + (y - sy) ** 2
            if sum(d < dq for d in nearest.values()) < k:
                out.add((s, t, 1 if side == "o" else 2))
    return out


def test_all_stops_as_queries_equal_brute_force_in_tiles_and_by_descent(spark, monkeypatch):
    routes, ends = plane(spark, random.Random(3))
    stops, points = build_stop_index(spark.createDataFrame(routes, ROUTE_POINTS)), build_endpoint_index(spark.createDataFrame(ends, ENDPOINTS))
    expected = brute(routes, ends, 4)
    descended = []
    monkeypatch.setattr("transitlens.operators.pruning.opened", lambda index, probes: descended.append(probes.count()) or lone.opened(index, probes))
    got = planner.vertex_omega(stops, points, (4,), method="queries").collect()
    assert {(r.stop_id, r.transition_id, s) for r in got for s in (1, 2) if r["mask"] & s} == expected
    # Most stops of the town are settled in tiles; those at its rim and far away are not.
    n_stops = stops.base.count()
    assert 0 < descended[0] < n_stops - 50


def test_tiles_leave_the_candidates_that_the_descent_leaves(spark, monkeypatch):
    routes, ends = plane(spark, random.Random(4))
    stops, points = build_stop_index(spark.createDataFrame(routes, ROUTE_POINTS)), build_endpoint_index(spark.createDataFrame(ends, ENDPOINTS))
    asked = stops.points().selectExpr("stop_id AS query_id", "0 AS q_idx", "x_m", "y_m", "CAST(NULL AS BIGINT) AS exclude_route_id")
    found = []
    for alone in (True, False):
        with monkeypatch.context() as m:
            if not alone:
                m.setattr("transitlens.operators.reverse.are_lone", lambda probes: False)
            probes = filtered_probes(stops, asked, 4)
            assert lone.by_ids(probes) == alone
            left = prune_endpoints(points, probes, 4, None, True, stops)
            counts = verify.nearer_counts(left, stops, probes, 4).filter("nearer < 4")
            ids = {r.probe_id: r.query_id for r in probes.select("probe_id", "query_id").collect()}
            found.append([{(ids[r.probe_id], *r[1:]) for r in rows.collect()} for rows in (left, counts)])
    assert found[0] == found[1]


def test_paths_in_depth_equal_paths_by_length():
    draw = random.Random(9)
    for _ in range(60):
        near = {u: [(v, draw.randint(1, 5)) for v in range(7) if v != u and draw.random() < 0.5] for u in range(7)}
        net = Network(near, {v: Points({(draw.randint(1, 5), draw.randint(1, 2)) for _ in range(draw.randint(0, 4))}) for v in range(7)})
        listed = list(paths_within(net, 0, 6, 11))
        assert sorted((n, p) for n, p, _ in all_paths(net, 0, 6, 11)) == listed
        for objective, sign in (("max", -1), ("min", 1)):
            for mode in ("any", "both"):
                best = min(((sign * served(net.points(p), mode), n, p) for n, p in listed), default=None)
                plan = best_by_enumeration(net, 0, 6, 11, objective, mode)
                assert (plan and (sign * plan.value, plan.length, plan.path, plan.labels)) == (best and (*best, len(listed)))
    assert [p for _, p, _ in all_paths(Network(), 3, 3, 0)] == [(3,)]
