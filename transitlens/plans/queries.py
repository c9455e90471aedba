"""Every method, variant, baseline, measure and operator as a query over the given tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import geometry as G
from ..operators import graph, knn, planner, trips
from ..operators.filtering import choose_filter_stops
from ..operators.reverse import probes_of, reverse_routes
from ..schema import TRANSITIONS, endpoints
from ..sources import fixtures as X
from ..streaming import transitions as stream
from . import metrics
from . import oracles as O
from .layout import StopIndex, append_transitions, build_endpoint_index, build_stop_index, cell_routes, endpoint_cells, expire, read_endpoints, stop_routes, write_endpoints
from .shared import drop_since, mark, scratch_path, written
from .workloads import chord_queries, planning_queries, random_queries, route_queries

#: The route that serves as a query where one is asked, and the planning queries' stops and limit in percent.
ROUTE = 51
STOPS, PERCENT = 6, 140
KS = (1, 5, 10, 15, 20, 25)
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def _add(name: str, run: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql is not None:
        SQL[name] = sql


def _points(spark: SparkSession, d: str) -> DataFrame:
    return endpoints(X.transitions(spark, d))


def _query(spark: SparkSession, d: str, rp: DataFrame | None = None) -> DataFrame:
    """A whole route as the query, itself out of the competition."""
    rp = X.route_points(spark, d) if rp is None else rp
    return route_queries(rp.filter(F.col("route_id") == ROUTE))


def _reverse(method: str, mode: str, k: int = 10, rule: str = "exact", large: bool = False) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, d: str) -> DataFrame:
        rp = written(X.route_points(spark, d), "route-points")
        points = endpoints(X.large_transitions(spark, d)) if large else _points(spark, d)
        return reverse_routes(rp, written(points, "endpoints"), _query(spark, d, rp), k, mode, rule, method)

    return run


for _mode in ("any", "both"):
    for _method in ("forward", "scan", "framework", "cell", "split"):
        _add(f"reverse_{_method}_{_mode}", _reverse(_method, _mode), O.reverse(O.whole_route(ROUTE), 10, _mode))
    _add(f"reverse_large_{_mode}", _reverse("split", _mode, large=True), O.reverse(O.whole_route(ROUTE), 10, _mode, trips=O.TR_LARGE))
_add("reverse_loose_any", _reverse("split", "any", rule="loose"), O.reverse(O.whole_route(ROUTE), 10, loose=True))
_add("reverse_point", lambda s, d: (lambda rp: reverse_routes(rp, written(_points(s, d), "endpoints"), _query(s, d, rp).filter("q_idx = 1"), 10))(written(X.route_points(s, d), "route-points")), O.reverse(O.whole_route(ROUTE) + " AND seq = 1", 10))


def _indexes(spark: SparkSession, d: str, large: bool = False) -> tuple:
    rp = written(X.route_points(spark, d), "route-points")
    points = endpoints(X.large_transitions(spark, d)) if large else _points(spark, d)
    return rp, build_stop_index(rp), build_endpoint_index(written(points, "endpoints"))


def _ranks(spark: SparkSession, d: str, large: bool = False, ks: tuple[int, ...] = KS, keep: Callable[[DataFrame], DataFrame] = lambda x: x) -> DataFrame:
    """``(k, transition_id, route_id, mask)``: for each k the routes that rank among the k nearest of a transition's ends. A route's own
    result, itself out of the competition, is the transitions that have it here."""
    return _forward(spark, d, lambda points, stops: knn.masks_by_rings(points, stops, ks, keep=keep), large)


def _forward(spark: SparkSession, d: str, run: Callable[[DataFrame, StopIndex], DataFrame], large: bool = False) -> DataFrame:
    """``run(points, stops)`` of a forward pass. It leaves its own tables only: route points go once they are indexed, endpoints once
    the distances of their nearest routes are written."""
    start = mark()
    _, stops, points = _indexes(spark, d, large)
    drop_since(spark, start, stops.base, points.points)
    indexed, found = mark(), run(points.points, stops)
    drop_since(spark, start, stops.base, until=indexed)
    return found


def _counted(found: DataFrame, *by: str) -> DataFrame:
    return found.groupBy(*by).agg(F.count("*").alias("n_any"), F.count_if(F.col("mask") == 3).alias("n_both"))


_MASKS = ", masks AS (SELECT k, transition_id, route_id, bit_or(side) AS mask FROM ranked, (SELECT unnest([1, 5, 10, 15, 20, 25]) AS k) WHERE rank <= k GROUP BY 1, 2, 3)"
_add(
    "nearest_routes_k",
    lambda s, d: _forward(s, d, lambda points, stops: knn.nearest_by_rings(points, stops, 10)).select("transition_id", "side", "route_id", "d2"),
    O.RANKED + " SELECT transition_id, CASE side WHEN 1 THEN 'o' ELSE 'd' END AS side, route_id, d AS d2 FROM ranked WHERE rank <= 10",
)
for _mode in ("any", "both"):
    _add(
        f"transition_routes_{_mode}",
        (lambda mode: lambda s, d: _forward(s, d, lambda points, stops: knn.masks_by_rings(points, stops, (10,), mode)).drop("k"))(_mode),
        O.RANKED + _MASKS + f" SELECT transition_id, route_id, CAST(mask AS INTEGER) AS mask FROM masks WHERE k = 10{'' if _mode == 'any' else ' AND mask = 3'}",
    )
_add("reverse_all_routes", lambda s, d: _counted(_ranks(s, d, ks=(10,)), "route_id"), O.RANKED + _MASKS + " SELECT route_id, count(*) AS n_any, CAST(count_if(mask = 3) AS BIGINT) AS n_both FROM masks WHERE k = 10 GROUP BY 1")
_add("reverse_all_routes_large", lambda s, d: _counted(_ranks(s, d, True, (10,)), "route_id"))
_add("sweep_k", lambda s, d: _counted(_ranks(s, d), "k"), O.RANKED + _MASKS + " SELECT CAST(k AS INTEGER) AS k, count(*) AS n_any, CAST(count_if(mask = 3) AS BIGINT) AS n_both FROM masks GROUP BY 1")
_add("sweep_k_large", lambda s, d: _counted(_ranks(s, d, True), "k"))


def _sweep(lengths: tuple[int, ...], intervals: tuple[int, ...], n: int = 5) -> Callable[[SparkSession, str], DataFrame]:
    """Generated queries, ``n`` of each length and interval, in one batch by the split method."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        rp, stops, points = _indexes(spark, d)
        parts = [random_queries(rp, n, m, step, seed=m).withColumn("query_id", (F.col("query_id") * 100 + m) * 10 + step // 1000) for m in lengths for step in intervals]
        asked = parts[0]
        for p in parts[1:]:
            asked = asked.unionByName(p)
        found = reverse_routes(stops, points, written(asked, "sweep-queries"), 10)
        found = found.withColumns({"length": F.expr("query_id div 10 % 100"), "interval_km": F.expr("query_id % 10")})
        return _counted(found, "length", "interval_km")

    return run


_add("sweep_length", _sweep(tuple(range(3, 11)), (3000,)))
_add("sweep_interval", _sweep((5,), tuple(range(1000, 7000, 1000))))


def _mode_invariant(spark: SparkSession, d: str) -> DataFrame:
    """Transitions that a route wins by both ends but not by any: none."""
    o, to = knn.ends(0)
    wrong = F.size(F.array_except(F.array_intersect(o, to), F.array_union(o, to)))
    return _forward(spark, d, lambda points, stops: knn.sides_by_rings(points, stops, (10,))).agg(F.coalesce(F.sum(wrong), F.lit(0)).cast("bigint").alias("n"))


def _point_invariant(spark: SparkSession, d: str) -> DataFrame:
    """Endpoints nearer to one of a route's stops than to the query, and among them those not nearer to the route: none."""
    rp = X.route_points(spark, d)
    index, asked = build_stop_index(rp), probes_of(_query(spark, d, rp), False).select("all_q")
    dq = G.nearest_sq(F.col("x_m"), F.col("y_m"), F.col("all_q"))
    ends = written(_points(spark, d).select("transition_id", "side", "x_m", "y_m").distinct().join(F.broadcast(asked)).withColumn("dq", dq).drop("all_q"), "ends")
    near = ends.filter("dq > 0").select("transition_id", "side", "x_m", "y_m", F.array(F.least(F.lit(1500 * 1500).cast("bigint"), F.col("dq") - 1)).alias("kth"), "dq")
    count = lambda x: x.agg(F.coalesce(F.sum(F.size("routes")), F.lit(0)).cast("bigint").alias("n"), F.coalesce(F.sum(F.size(F.filter("d2", lambda v: v >= F.col("dq")))), F.lit(0)).cast("bigint").alias("n_wrong"))
    again = knn.ends_again(near)
    if again is None:
        return count(knn.lists_within(near, index, ("dq",)))
    # Ends at several places: a route counts once.
    once = count(knn.lists_within(near.join(again, ["transition_id", "side"], "left_anti"), index, ("dq",)))
    more = knn.lists_within(near.join(again, ["transition_id", "side"], "left_semi"), index, ("dq",)).select("transition_id", "side", "dq", F.explode(F.arrays_zip("routes", "d2")).alias("p"))
    more = more.groupBy("transition_id", "side", "p.routes").agg(F.min("p.d2").alias("d2"), F.min("dq").alias("dq")).agg(F.count("*").alias("n"), F.count_if(F.col("d2") >= F.col("dq")).alias("n_wrong"))
    return once.unionByName(more).agg(F.sum("n").alias("n"), F.sum("n_wrong").alias("n_wrong"))


_add("both_within_any", _mode_invariant, "SELECT CAST(0 AS BIGINT) AS n")
_add(
    "point_implies_route",
    _point_invariant,
    f"WITH {O.RP}, {O.TR}, {O.EP}, {O.ST}, q AS ({O.whole_route(ROUTE)}), e AS (SELECT transition_id, side, ep.x, ep.y, min((ep.x - q.x) * (ep.x - q.x) + (ep.y - q.y) * (ep.y - q.y)) AS dq FROM ep CROSS JOIN q GROUP BY ALL) "
    "SELECT count(*) AS n, CAST(0 AS BIGINT) AS n_wrong FROM (SELECT DISTINCT transition_id, side, route_id FROM e JOIN st s ON s.x BETWEEN e.x - 1500 AND e.x + 1500 AND s.y BETWEEN e.y - 1500 AND e.y + 1500 JOIN through USING (stop_id) "
    "WHERE (e.x - s.x) * (e.x - s.x) + (e.y - s.y) * (e.y - s.y) <= 2250000 AND (e.x - s.x) * (e.x - s.x) + (e.y - s.y) * (e.y - s.y) < dq)",
)

_add(
    "stop_routes",
    lambda s, d: stop_routes(X.route_points(s, d)).select("stop_id", "x_m", "y_m", F.array_join(F.col("routes").cast("array<string>"), ",").alias("routes"), F.col("n_routes").cast("bigint").alias("n_routes")),
    f"WITH {O.RP}, {O.ST} SELECT stop_id, x AS x_m, y AS y_m, string_agg(CAST(route_id AS VARCHAR), ',' ORDER BY route_id) AS routes, count(*) AS n_routes FROM st JOIN through USING (stop_id) GROUP BY 1, 2, 3",
)
_LEVELS = " UNION ALL ".join(f"SELECT CAST({s} AS INTEGER) AS level, {O.cell('x_m', 'y_m', s)} AS cell, * FROM rp" for s in G.LEVELS)
_add(
    "cell_routes",
    lambda s, d: cell_routes(stop_routes(X.route_points(s, d))).select("level", "cell", "box.x_lo", "box.x_hi", "box.y_lo", "box.y_hi", F.size("routes").cast("bigint").alias("n_routes")),
    f"WITH {O.RP}, c AS ({_LEVELS}) SELECT level, cell, min(x_m) AS x_lo, max(x_m) AS x_hi, min(y_m) AS y_lo, max(y_m) AS y_hi, count(DISTINCT route_id) AS n_routes FROM c GROUP BY 1, 2",
)
_DESCENT = " UNION ALL ".join(f"SELECT CAST({s} AS INTEGER) AS level, {O.cell('x', 'y', s)} AS cell, * FROM ep" for s in G.DESCENT)
_add(
    "endpoint_cells",
    lambda s, d: endpoint_cells(_points(s, d)).select("level", "cell", "box.x_lo", "box.x_hi", "box.y_lo", "box.y_hi", "n"),
    f"WITH {O.TR}, {O.EP}, c AS ({_DESCENT}) SELECT level, cell, min(x) AS x_lo, max(x) AS x_hi, min(y) AS y_lo, max(y) AS y_hi, count(*) AS n FROM c GROUP BY 1, 2",
)


def _filter_stops_sound(spark: SparkSession, d: str) -> DataFrame:
    """Stops of the filter set, of pruned cells and pruned by themselves: together each stop once."""
    rp = written(X.route_points(spark, d), "route-points")
    index = build_stop_index(rp)
    probes = probes_of(_query(spark, d, rp), False)
    chosen, cells, points = choose_filter_stops(index, probes, 10)
    stops = index.points()
    in_cells = [stops.withColumn("cell", G.cell_at(F.col("x_m"), F.col("y_m"), s)).join(cells.filter(F.col("level") == s).select("cell"), "cell", "left_semi").filter(F.size(F.array_remove("routes", F.lit(ROUTE))) > 0).select("stop_id") for s in G.DESCENT]
    every = chosen.select("stop_id").unionByName(points.select("stop_id"))
    for part in in_cells:
        every = every.unionByName(part)
    return every.agg(F.count("*").alias("n_stops"), F.count_distinct("stop_id").alias("n_distinct"))


_add("filter_stops_sound", _filter_stops_sound, f"WITH {O.RP} SELECT count(DISTINCT stop_id) AS n_stops, count(DISTINCT stop_id) AS n_distinct FROM rp WHERE route_id <> {ROUTE}")


def _trips(large: bool) -> Callable[[SparkSession, str], DataFrame]:
    return lambda s, d: (X.large_transitions if large else X.transitions)(s, d).select("transition_id", "user_id", "o_x", "o_y", "d_x", "d_y", F.unix_micros("ts").alias("ts_us"))


_add("checkin_transitions", _trips(False), O.transitions_text())
_add("large_transitions", _trips(True), O.transitions_text(True))
_add("path_length", lambda s, d: graph.path_length(X.route_points(s, d)), f"WITH {O.RP}, {O.SEGMENTS} SELECT route_id, CAST(coalesce(sum(n), 0) AS BIGINT) AS length_m, count(*) AS n_stops FROM seg GROUP BY 1")
_RATIO = f"""WITH {O.RP}, {O.SEGMENTS}, l AS (SELECT route_id, CAST(coalesce(sum(n), 0) AS BIGINT) AS length_m, count(*) AS n_stops FROM seg GROUP BY 1),
c AS (SELECT route_id, arg_min(x_m, seq) AS ax, arg_min(y_m, seq) AS ay, arg_max(x_m, seq) AS bx, arg_max(y_m, seq) AS by_ FROM rp GROUP BY 1),
r AS (SELECT route_id, length_m, n_stops, sqrt(CAST((ax - bx) * (ax - bx) + (ay - by_) * (ay - by_) AS DOUBLE)) AS chord FROM l JOIN c USING (route_id))"""
_add("detour_ratio", lambda s, d: metrics.detour_ratio(X.route_points(s, d)), _RATIO + " SELECT route_id, length_m, n_stops, round(chord, 6) AS chord_m, round(length_m / n_stops, 6) AS interval_m, round(CASE WHEN chord > 0 THEN length_m / chord END, 6) AS ratio FROM r")
_add(
    "detour_hist",
    lambda s, d: metrics.histogram(metrics.detour_ratio(X.route_points(s, d)), "ratio", 1.0, 2.0, 10),
    _RATIO + ", h AS (SELECT round(CASE WHEN chord > 0 THEN length_m / chord END, 6) AS ratio FROM r) SELECT CAST(CASE WHEN ratio < 1 THEN 0 WHEN ratio >= 2 THEN 11 ELSE floor((ratio - 1.0) / 1.0 * 10) + 1 END AS BIGINT) AS bin, count(*) AS n FROM h WHERE ratio IS NOT NULL GROUP BY 1",
)
_add(
    "dataset_stats",
    lambda s, d: metrics.dataset_stats(X.route_points(s, d), X.transitions(s, d)),
    f"WITH {O.RP}, {O.TR}, {O.SEGMENTS}, {O.EDGES}, o AS (SELECT count(DISTINCT route_id) AS routes, count(DISTINCT stop_id) AS stops, min(x_m) AS x_lo, max(x_m) AS x_hi, min(y_m) AS y_lo, max(y_m) AS y_hi, (SELECT count(*) FROM edges WHERE src < dst) AS edges, (SELECT count(*) FROM tr) AS transitions FROM rp) SELECT name, CAST(value AS BIGINT) AS value FROM (UNPIVOT o ON COLUMNS(*) INTO NAME name VALUE value)",
)
_add("graph_edges", lambda s, d: graph.build(X.route_points(s, d)), f"WITH {O.RP}, {O.SEGMENTS}, {O.EDGES} SELECT src, dst, CAST(length_m AS BIGINT) AS length_m FROM edges")


#: Distance up to which shortest paths are listed.
CAP_M = 4000


def _shortest(spark: SparkSession, d: str) -> DataFrame:
    rp = written(X.route_points(spark, d), "route-points")
    target = rp.filter((F.col("route_id") == ROUTE) & (F.col("seq") == 1)).select(F.col("stop_id").alias("target"))
    return graph.shortest_to(graph.build(rp), target, 6000)


_add("shortest_to", _shortest, O.shortest(f"SELECT stop_id AS target FROM rp WHERE route_id = {ROUTE} AND seq = 1", 6000))
_add("all_pairs_near", lambda s, d: graph.all_pairs(graph.build(X.route_points(s, d)), CAP_M), O.shortest("SELECT DISTINCT stop_id AS target FROM rp", CAP_M))


def _vertex_omega(spark: SparkSession, d: str, ks: tuple[int, ...], method: str = "rings") -> DataFrame:
    if method == "rings":
        return _forward(spark, d, lambda points, stops: planner.vertex_omega(stops, build_endpoint_index(points), ks))
    _, stops, points = _indexes(spark, d)
    return planner.vertex_omega(stops, points, ks, method=method)


_add("vertex_omega", lambda s, d: _vertex_omega(s, d, (1,)), O.vertex_omega())
_add("vertex_omega_ks", lambda s, d: _counted(_vertex_omega(s, d, (1, 5, 10)), "k", "stop_id"), O.vertex_counts((1, 5, 10)))


def _path_omega(spark: SparkSession, d: str) -> DataFrame:
    start = mark()
    rp, stops, points = _indexes(spark, d)
    path = written(rp.filter(F.col("route_id") == ROUTE).select(F.col("route_id").alias("query_id"), "stop_id"), "path")
    drop_since(spark, start, path, stops.base, points.points)
    indexed, omega = mark(), planner.vertex_omega(stops, points, (10,), path).drop("k")
    drop_since(spark, start, path, stops.base, until=indexed)
    return planner.path_omega(path, omega)


_add("path_omega", _path_omega, O.reverse(f"SELECT route_id AS query_id, x_m AS x, y_m AS y, CAST(NULL AS BIGINT) AS excluded FROM rp WHERE route_id = {ROUTE}", 10))


def _planner(spark: SparkSession, d: str, k: int = 10, results: bool = True) -> tuple:
    """All that the planners need: the first stops of every route, all stops, endpoints, queries (between both ends of those first stops),
    edges, places and results of the stops. With ``results`` the endpoints are no longer there, without them they are and results are not."""
    start = mark()
    rp, stops, points = _indexes(spark, d)
    heads = written(rp.filter(F.col("seq") <= STOPS), "route-heads")
    asked = written(planning_queries(heads, STOPS, PERCENT), "planning")
    edges, where = written(graph.build(rp), "edges"), stops.points().select("stop_id", "x_m", "y_m")
    drop_since(spark, start, heads, stops.base, points.points, asked, edges)
    if not results:
        return heads, stops, points, asked, edges, where, None
    omega = written(planner.vertex_omega(stops, points, (k,)).drop("k"), "omega")
    drop_since(spark, start, heads, stops.base, asked, edges, omega)
    return heads, stops, None, asked, edges, where, omega


def _plan(method: str, objective: str, mode: str, dominance: str = "contain") -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, d: str) -> DataFrame:
        _, stops, points, asked, edges, where, omega = _planner(spark, d, results=method != "enumerate")
        if method == "enumerate":
            return planner.plan_by_queries(asked, edges, stops, points, 10, objective, mode).drop("labels")
        return planner.plan_routes(asked, edges, where, omega, objective, mode, method, dominance).drop("labels")

    return run


for _objective in ("max", "min"):
    for _mode in ("any", "both"):
        for _method in ("search", "pre", "enumerate"):
            _add(f"plan_{_method}_{_objective}_{_mode}", _plan(_method, _objective, _mode), O.plan(_objective, _mode, STOPS, PERCENT))
_add("plan_search_count_dominance", _plan("search", "max", "any", "count"))
_add("plan_shortest", _plan("shortest", "max", "any"), O.plan("shortest", "any", STOPS, PERCENT))


def _count_rule_gap(spark: SparkSession, d: str) -> DataFrame:
    """How the published dominance rule does against the optimum: queries, queries that lose, transitions won and possible."""
    _, _, _, asked, edges, where, omega = _planner(spark, d)
    best, found = (planner.plan_routes(asked, edges, where, omega, dominance=x).select("query_id", F.col("n_transitions").alias(x)) for x in ("contain", "count"))
    return best.join(found, "query_id").agg(F.count("*").alias("n_queries"), F.count_if(F.col("count") < F.col("contain")).alias("n_lost"), F.sum("count").alias("won"), F.sum("contain").alias("best"))


def _replanned(spark: SparkSession, d: str) -> DataFrame:
    """Every route's first stops re-planned under their own length: transitions of the old way and of the new one."""
    rp, _, _, _, edges, where, omega = _planner(spark, d)
    asked = written(planning_queries(rp, STOPS, 100), "planning")
    old = planner.path_omega(rp.filter(F.col("seq") <= STOPS).select(F.col("route_id").alias("query_id"), "stop_id"), omega).groupBy("query_id").agg(F.count("*").alias("old"))
    new = planner.plan_routes(asked, edges, where, omega).select("query_id", "length_m", F.col("n_transitions").alias("new"))
    return asked.select("query_id", "max_len_m").join(new, "query_id").join(old, "query_id", "left").select("query_id", "max_len_m", "length_m", F.coalesce("old", F.lit(0)).alias("old"), "new")


def _plan_sweep(ratios: tuple[int, ...], chords: tuple[int, ...]) -> Callable[[SparkSession, str], DataFrame]:
    """Planning queries by chord (km) and limit (percent of the chord): how many have a path, and what the best of them win."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        _, stops, _, _, edges, where, omega = _planner(spark, d)
        out = None
        for chord in chords:
            pairs = written(chord_queries(where, edges, chord * 1000), "planning-pairs")
            for ratio in ratios:
                asked = pairs.withColumn("max_len_m", F.expr(f"chord_m * {ratio} div 100"))
                for objective in ("max", "min"):
                    best = planner.plan_routes(asked, edges, where, omega, objective)
                    row = best.agg(F.count("*").alias("n_found"), F.coalesce(F.sum("n_transitions"), F.lit(0)).alias("n_transitions"), F.coalesce(F.sum("labels"), F.lit(0)).alias("labels"))
                    row = row.select(F.lit(chord).alias("chord_km"), F.lit(ratio).alias("ratio"), F.lit(objective).alias("objective"), "*")
                    out = row if out is None else out.unionByName(row)
        return out

    return run


_add("plan_count_rule_gap", _count_rule_gap)
_add("plan_replanned_routes", _replanned, O.replanned(STOPS))
_add("plan_sweep_ratio", _plan_sweep((100, 120, 140, 160, 180, 200), (3,)))
_add("plan_sweep_chord", _plan_sweep((140,), (1, 2, 3, 4, 5)))


def _four_routes(spark: SparkSession, d: str) -> DataFrame:
    """Original, shortest, max and min route between the ends of a route's first stops."""
    rp, _, _, asked, edges, where, omega = _planner(spark, d)
    own, asked = rp.filter((F.col("route_id") == ROUTE) & (F.col("seq") <= STOPS)), asked.filter(F.col("query_id") == ROUTE)
    served = planner.path_omega(own.select(F.col("route_id").alias("query_id"), "stop_id"), omega).agg(F.count("*").alias("n_transitions"))
    parts = [graph.path_length(own).join(F.broadcast(served)).select(F.lit("original").alias("kind"), "length_m", "n_transitions", "n_stops")]
    for kind, method, objective in (("shortest", "shortest", "max"), ("max", "search", "max"), ("min", "search", "min")):
        parts.append(planner.plan_routes(asked, edges, where, omega, objective, "any", method).select(F.lit(kind).alias("kind"), "length_m", "n_transitions", "n_stops"))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


_add("four_routes", _four_routes, O.four_routes(ROUTE, STOPS, PERCENT))


def _boardings(spark: SparkSession, d: str) -> DataFrame:
    return trips.boardings(X.transitions(spark, d), stop_routes(X.route_points(spark, d)))


_BOARD = f"WITH {O.RP}, {O.TR}, {O.ST}, {O.BOARD}"
_add("top_routes", lambda s, d: _boardings(s, d).groupBy("route_id").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "route_id").limit(20), _BOARD + " SELECT route_id, count(*) AS n FROM board GROUP BY 1 ORDER BY n DESC, route_id LIMIT 20")
_add("ridership_by_period", lambda s, d: _boardings(s, d).groupBy(F.hour("ts").cast("bigint").alias("hour")).agg(F.count_distinct("transition_id").alias("n_transitions"), F.count("*").alias("n_boardings")), _BOARD + " SELECT CAST(hour(ts) AS BIGINT) AS hour, count(DISTINCT transition_id) AS n_transitions, count(*) AS n_boardings FROM board GROUP BY 1")


def _regions(spark: SparkSession, d: str) -> DataFrame:
    read = lambda t: spark.read.parquet(f"{d}/{t}.parquet")
    where = read("supplier").join(read("nation"), F.col("s_nationkey") == F.col("n_nationkey")).join(read("region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return _boardings(spark, d).withColumn("s_suppkey", F.expr("route_id div 10")).join(where.select("s_suppkey", "r_name", "n_name"), "s_suppkey")


_add(
    "ridership_rollup",
    lambda s, d: _regions(s, d).rollup("r_name", "n_name").agg(F.count("*").alias("n")).select(F.coalesce("r_name", F.lit("all")).alias("region"), F.coalesce("n_name", F.lit("all")).alias("nation"), "n"),
    _BOARD + " SELECT coalesce(r_name, 'all') AS region, coalesce(n_name, 'all') AS nation, count(*) AS n FROM board JOIN supplier ON s_suppkey = route_id // 10 JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)",
)
_add(
    "route_profiles",
    lambda s, d: _boardings(s, d).join(s.read.parquet(f"{d}/events.parquet").select(F.col("event_id").alias("transition_id"), "event_type"), "transition_id").groupBy("route_id", "event_type").agg(F.count("*").alias("n")).withColumn("rank", F.row_number().over(Window.partitionBy("route_id").orderBy(F.desc("n"), "event_type")).cast("bigint")).filter("rank <= 3"),
    _BOARD + ", g AS (SELECT route_id, event_type, count(*) AS n FROM board JOIN events ON event_id = transition_id GROUP BY 1, 2) SELECT route_id, event_type, n, row_number() OVER (PARTITION BY route_id ORDER BY n DESC, event_type) AS rank FROM g QUALIFY row_number() OVER (PARTITION BY route_id ORDER BY n DESC, event_type) <= 3",
)
_add(
    "route_overlap",
    lambda s, d: (lambda b: b.filter(F.col("route_id") == ROUTE).select("transition_id").intersect(b.filter(F.col("route_id") != ROUTE).select("transition_id")).agg(F.count("*").alias("shared")))(_boardings(s, d)),
    _BOARD + f" SELECT count(*) AS shared FROM (SELECT transition_id FROM board WHERE route_id = {ROUTE} INTERSECT SELECT transition_id FROM board WHERE route_id <> {ROUTE})",
)
_add("uncovered_transitions", lambda s, d: X.transitions(s, d).select("transition_id").join(_boardings(s, d), "transition_id", "left_anti"), _BOARD + " SELECT transition_id FROM tr ANTI JOIN board USING (transition_id)")
_add(
    "within_radius",
    lambda s, d: trips.within_radius(_points(s, d).withColumn("side", F.when(F.col("side") == "o", 1).otherwise(2)), stop_routes(X.route_points(s, d)), 1500).select("transition_id", "side", "stop_id", "d2"),
    f"WITH {O.RP}, {O.TR}, {O.EP}, {O.ST} SELECT transition_id, side, stop_id, (ep.x - s.x) * (ep.x - s.x) + (ep.y - s.y) * (ep.y - s.y) AS d2 FROM ep JOIN st s ON s.x BETWEEN ep.x - 1500 AND ep.x + 1500 AND s.y BETWEEN ep.y - 1500 AND ep.y + 1500 WHERE (ep.x - s.x) * (ep.x - s.x) + (ep.y - s.y) * (ep.y - s.y) <= 2250000",
)
_add(
    "asof_checkin",
    lambda s, d: trips.last_before(
        s.read.parquet(f"{d}/orders.parquet").select("o_orderkey", F.expr("o_custkey % 150").alias("user_id"), F.to_timestamp_ntz(F.lit("2024-01-15 00:00:00")).cast("timestamp").alias("ts")),
        s.read.parquet(f"{d}/events.parquet").select("user_id", F.col("ts").cast("timestamp").alias("ts"), "event_id"), "user_id", "ts", "event_id",
    ).select("o_orderkey", "event_id"),
    "SELECT o_orderkey, event_id FROM (SELECT o_orderkey, o_custkey % 150 AS user_id FROM orders) o LEFT JOIN (SELECT user_id, arg_max(event_id, ts) AS event_id FROM events WHERE ts <= TIMESTAMP '2024-01-15 00:00:00' GROUP BY 1) e USING (user_id)",
)
_add(
    "turn_angles",
    lambda s, d: X.route_points(s, d).select("route_id", "seq", *(F.lag(c).over(Window.partitionBy("route_id").orderBy("seq")).alias(f"p{c}") for c in ("x_m", "y_m")), *(F.lead(c).over(Window.partitionBy("route_id").orderBy("seq")).alias(f"n{c}") for c in ("x_m", "y_m")), "x_m", "y_m").filter("px_m IS NOT NULL AND nx_m IS NOT NULL").select("route_id", "seq", F.expr("(x_m - px_m) * (nx_m - x_m) + (y_m - py_m) * (ny_m - y_m)").alias("dot")),
    f"WITH {O.RP}, a AS (SELECT route_id, seq, (x_m - lag(x_m) OVER w) * (lead(x_m) OVER w - x_m) + (y_m - lag(y_m) OVER w) * (lead(y_m) OVER w - y_m) AS dot FROM rp WINDOW w AS (PARTITION BY route_id ORDER BY seq)) SELECT route_id, seq, dot FROM a WHERE dot IS NOT NULL",
)


def _pruning(method: str) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, d: str) -> DataFrame:
        _, stops, points = _indexes(spark, d)
        return metrics.pruning_power(stops, points, _query(spark, d), 10, method)

    return run


for _method in ("framework", "cell", "split"):
    _add(f"pruning_power_{_method}", _pruning(_method))


def _stream_pairs(spark: SparkSession, d: str) -> DataFrame:
    events = stream.stream_table(spark, d, "events").select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"), F.round(F.col("value") * 100).cast("bigint").alias("x"), F.get_json_object("props", "$.k").cast("bigint").alias("y"))
    return stream.drained(stream.pair_checkins(events), "stream-pairs").select("transition_id", "user_id", "o_x", "o_y", "d_x", "d_y")


_add(
    "stream_transitions",
    _stream_pairs,
    "SELECT * FROM (SELECT event_id AS transition_id, user_id, lag(CAST(round(value * 100) AS BIGINT)) OVER w AS o_x, lag(CAST(json_extract(props, '$.k') AS BIGINT)) OVER w AS o_y, CAST(round(value * 100) AS BIGINT) AS d_x, CAST(json_extract(props, '$.k') AS BIGINT) AS d_y FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) WHERE o_x IS NOT NULL",
)


def _stream_days(spark: SparkSession, d: str) -> DataFrame:
    events = stream.stream_table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return stream.drained(stream.window_counts(events), "stream-days", "complete").select(F.unix_micros("start").alias("start_us"), "n")


_add("stream_windows", _stream_days, "SELECT CAST(epoch_us(date_trunc('day', ts)) AS BIGINT) AS start_us, count(*) AS n FROM events GROUP BY 1")


def _stream_dedup(spark: SparkSession, d: str) -> DataFrame:
    events = stream.stream_table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return stream.drained(stream.deduplicated(events.select("event_id", "user_id", "ts")), "stream-dedup").select("event_id", "user_id")


_add("stream_dedup", _stream_dedup, "SELECT DISTINCT event_id, user_id FROM events")


def _stream_sessions(spark: SparkSession, d: str) -> DataFrame:
    events = stream.stream_table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return stream.drained(stream.session_counts(events), "stream-sessions", "complete").select("user_id", F.unix_micros("start").alias("start_us"), "n")


_add(
    "stream_sessions",
    _stream_sessions,
    "SELECT user_id, CAST(epoch_us(min(ts)) AS BIGINT) AS start_us, count(*) AS n FROM (SELECT user_id, ts, sum(gap) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS gap FROM events)) GROUP BY user_id, s",
)


def _stream_reverse(spark: SparkSession, d: str) -> DataFrame:
    """Trips that arrive as a stream, each classified once for a registered route."""
    rp, stops, _ = _indexes(spark, d)
    folder = scratch_path(spark, "arrivals")
    X.transitions(spark, d).repartition(3, "user_id").write.parquet(f"{folder}/transitions.parquet")
    arriving = spark.readStream.schema(TRANSITIONS).option("maxFilesPerTrigger", 1).parquet(f"{folder}/transitions.parquet")
    return stream.classify(arriving, stops, written(_query(spark, d, rp), "registered"), 10)


_add("stream_reverse", _stream_reverse, O.reverse(O.whole_route(ROUTE), 10))


def _updated_index(spark: SparkSession, d: str, keep: bool) -> DataFrame:
    """A stored index that was filled in two parts and lost its oldest days, asked for one route."""
    rp, stops, _ = _indexes(spark, d)
    path = scratch_path(spark, "stored")
    rows, old = _points(spark, d), F.col("ts") < F.lit("2024-01-16").cast("timestamp")
    write_endpoints(rows.filter(old), path)
    append_transitions(rows.filter(~old), path)
    if not keep:
        expire(spark, path, "2024-01-10")
    return reverse_routes(stops, read_endpoints(spark, path, since="2024-01-01"), _query(spark, d, rp), 10)


_add("reverse_appended", lambda s, d: _updated_index(s, d, True), O.reverse(O.whole_route(ROUTE), 10))
_add("reverse_expired", lambda s, d: _updated_index(s, d, False), O.reverse(O.whole_route(ROUTE), 10, trips=O.TR_LATE))


def _profiles(spark: SparkSession, d: str) -> DataFrame:
    """The commonest kinds of check-in among the transitions that each route wins."""
    events = spark.read.parquet(f"{d}/events.parquet").select(F.col("event_id").alias("transition_id"), "event_type")
    kinds = _ranks(spark, d, ks=(10,), keep=lambda x: x.join(events, "transition_id"))
    rank = F.row_number().over(Window.partitionBy("route_id").orderBy(F.desc("n"), "event_type")).cast("bigint")
    return kinds.groupBy("route_id", "event_type").agg(F.count("*").alias("n")).withColumn("rank", rank).filter("rank <= 3")


_add("advertising_profiles", _profiles, O.RANKED + _MASKS + ", g AS (SELECT route_id, event_type, count(*) AS n FROM masks JOIN events ON event_id = transition_id WHERE k = 10 GROUP BY 1, 2) SELECT *, row_number() OVER (PARTITION BY route_id ORDER BY n DESC, event_type) AS rank FROM g QUALIFY row_number() OVER (PARTITION BY route_id ORDER BY n DESC, event_type) <= 3")
_add(
    "won_by_period",
    lambda s, d: _ranks(s, d, ks=(10,), keep=lambda x: x.join(X.transitions(s, d).select("transition_id", F.hour("ts").cast("bigint").alias("hour")), "transition_id")).groupBy("route_id", "hour").agg(F.count("*").alias("n")),
    O.RANKED + _MASKS + " SELECT route_id, CAST(hour(ts) AS BIGINT) AS hour, count(*) AS n FROM masks JOIN tr USING (transition_id) WHERE k = 10 GROUP BY 1, 2",
)


def _phases(spark: SparkSession, d: str) -> DataFrame:
    """Seconds and counts of each phase, by method and k, for one whole route; the seconds differ from run to run."""
    rp, stops, points = _indexes(spark, d)
    asked = written(_query(spark, d, rp), "phase-query")
    rows = [(m, k, *r) for m in ("framework", "cell", "split") for k in (1, 10, 25) for r in metrics.phases(stops, points, asked, k, m)]
    return spark.createDataFrame(rows, "method string, k int, phase string, seconds double, rows long")


_add("reverse_phases", _phases)
_add("stop_heat", lambda s, d: X.route_points(s, d).groupBy(G.cell_at(F.col("x_m"), F.col("y_m"), 12).alias("cell")).agg(F.count("*").alias("n_points"), F.count_distinct("route_id").alias("n_routes")), f"WITH {O.RP} SELECT {O.cell('x_m', 'y_m', 12)} AS cell, count(*) AS n_points, count(DISTINCT route_id) AS n_routes FROM rp GROUP BY 1")
for _column, _low, _high in (("chord_m", 0, 200_000), ("interval_m", 800, 1300), ("n_stops", 0, 200)):
    _add(
        f"hist_{_column}",
        (lambda c, lo, hi: lambda s, d: metrics.histogram(metrics.detour_ratio(X.route_points(s, d)), c, lo, hi, 20))(_column, _low, _high),
        _RATIO + f", h AS (SELECT round(chord, 6) AS chord_m, round(length_m / n_stops, 6) AS interval_m, n_stops FROM r) SELECT CAST(CASE WHEN {_column} < {_low} THEN 0 WHEN {_column} >= {_high} THEN 21 ELSE floor(({_column} - {_low}.0) / {_high - _low}.0 * 20) + 1 END AS BIGINT) AS bin, count(*) AS n FROM h GROUP BY 1",
    )
