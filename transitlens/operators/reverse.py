"""Reverse route queries: the transitions that rank a query route among their k nearest routes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import geometry as G
from ..plans.layout import EndpointIndex, StopIndex, build_endpoint_index, build_stop_index, stop_routes
from ..plans.shared import few, written
from ..schema import QUERY_POINTS
from .filtering import SECTORS, SEEDS, choose_filter_stops, route_shapes, seed_stops, with_stops
from .lone import are_lone, with_seeds
from .pruning import prune_endpoints
from .verify import PROBES, nearer_counts

METHODS = ("forward", "scan", "framework", "cell", "split")
#: Stops up to which the exhaustive methods broadcast and pair them with every endpoint.
SCAN_STOPS = 100_000


def query_frame(spark: SparkSession, points: list[tuple[int, int]], query_id: int = 0, exclude_route_id: int | None = None) -> DataFrame:
    """Query points of one route, repeated points once."""
    if not points:
        raise ValueError("a query needs a point")
    distinct = list(dict.fromkeys((int(x), int(y)) for x, y in points))
    return spark.createDataFrame([(query_id, i, x, y, exclude_route_id) for i, (x, y) in enumerate(distinct)], QUERY_POINTS)


def probes_of(queries: DataFrame, split: bool) -> DataFrame:
    """``(probe_id, query_id, q_idx, q, all_q, exclude_route_id)``: a probe per query, or one per query point; written.

    ``q`` is what a probe prunes for, ``all_q`` the whole query, and ``q_idx`` is null for a whole query.
    """
    whole = queries.groupBy("query_id").agg(F.array_sort(F.collect_set(F.struct("q_idx", "x_m", "y_m"))).alias("all_q"), F.max("exclude_route_id").alias("exclude_route_id"))
    if split:
        each = whole.select("query_id", F.explode("all_q").alias("p"), "all_q", "exclude_route_id")
        probes = each.select("query_id", F.col("p.q_idx").alias("q_idx"), F.array("p").alias("q"), "all_q", "exclude_route_id")
    else:
        probes = whole.select("query_id", F.lit(None).cast("int").alias("q_idx"), F.col("all_q").alias("q"), "all_q", "exclude_route_id")
    return written(probes.select(F.monotonically_increasing_id().alias("probe_id"), "*"), "probe-points")


def apply_mode(points: DataFrame, mode: str) -> DataFrame:
    """``(query_id, transition_id, side)`` to ``(query_id, transition_id, mask)``: 1 origin, 2 destination, 3 both."""
    if mode not in ("any", "both"):
        raise ValueError(f"mode {mode!r}")
    mask = F.bit_or(F.when(F.col("side") == "o", 1).otherwise(2)).alias("mask")
    found = points.groupBy("query_id", "transition_id").agg(mask)
    return found if mode == "any" else found.filter("mask = 3")


def _need(k: int, rank_rule: str) -> int:
    if k < 1 or rank_rule not in ("exact", "loose"):
        raise ValueError(f"k {k}, rank_rule {rank_rule!r}")
    return k if rank_rule == "exact" else k + 1


def _exhaustive(route_points: DataFrame, endpoints: DataFrame, queries: DataFrame, need: int, ranked: bool) -> DataFrame:
    """Result points by pairing every endpoint with every stop; guarded by the number of stops."""
    stops = written(stop_routes(route_points), "scan-stops")
    if stops.count() > SCAN_STOPS:
        raise ValueError(f"more than {SCAN_STOPS} stops: use framework, cell or split")
    probes = probes_of(queries, False).select("query_id", F.col("all_q"), "exclude_route_id")
    rows = endpoints.select("transition_id", "side", "x_m", "y_m").join(few(probes, PROBES))
    rows = rows.withColumn("dq", G.nearest_sq(F.col("x_m"), F.col("y_m"), F.col("all_q"))).drop("all_q")
    keys = ["query_id", "transition_id", "side"]
    side = stops.select(F.col("x_m").alias("sx"), F.col("y_m").alias("sy"), "routes")
    d2 = G.sq_dist(F.col("x_m"), F.col("y_m"), F.col("sx"), F.col("sy"))
    allowed = "exclude_route_id IS NULL OR route_id <> exclude_route_id"
    if ranked:
        # All routes by distance, the query as one more of them: ties never push it back.
        near = rows.crossJoin(F.broadcast(side)).withColumn("d2", d2).select(*keys, "exclude_route_id", "d2", F.explode("routes").alias("route_id")).filter(allowed)
        dist = near.groupBy(*keys, "route_id").agg(F.min("d2").alias("d2")).unionByName(rows.select(*keys, F.lit(None).cast("long").alias("route_id"), F.col("dq").alias("d2")))
        rank = F.rank().over(Window.partitionBy(*keys).orderBy("d2"))
        return dist.withColumn("rank", rank).filter(F.col("route_id").isNull() & (F.col("rank") <= need)).select(*keys)
    nearer = rows.join(F.broadcast(side), d2 < F.col("dq")).select(*keys, "exclude_route_id", F.explode("routes").alias("route_id")).filter(allowed)
    counts = nearer.groupBy(*keys).agg(F.count_distinct("route_id").alias("nearer"))
    return rows.select(*keys).join(counts, keys, "left").filter(F.coalesce("nearer", F.lit(0)) < need).select(*keys)


def filtered_probes(stops: StopIndex, queries: DataFrame, need: int, method: str = "split", order: str = "distance", credit: str = "crossover", descend_routes: bool | None = None, seeds: int = SEEDS) -> DataFrame:
    """The filter step: probes with the stops they prune with; written.

    Any subset of the stops prunes soundly, and what a probe carries must stay small: its seeds, a fixed number around each point, and
    with ``descend_routes`` (the default for whole queries) the nearest of the stops that a descent through the route cells leaves, four
    times as many.
    """
    probes = probes_of(queries, method == "split")
    if method == "split" and not descend_routes and (order, credit) == ("distance", "crossover") and are_lone(probes):
        return written(with_seeds(stops, probes, seeds, SECTORS), "probes")
    chosen = seed_stops(stops, probes, order, seeds, credit)
    if descend_routes or descend_routes is None and method != "split":
        left_over, _, _ = choose_filter_stops(stops, probes, need, True, credit, order, method == "cell", seeds)
        near = left_over.join(few(probes.select("probe_id", "q"), PROBES), "probe_id").withColumn("_d", G.nearest_sq(F.col("x_m"), F.col("y_m"), F.col("q")))
        nth = F.row_number().over(Window.partitionBy("probe_id").orderBy("_d", "stop_id"))
        chosen = near.withColumn("_n", nth).filter(F.col("_n") <= 4 * seeds).select(chosen.columns).unionByName(chosen).dropDuplicates(["probe_id", "stop_id"])
    return written(with_stops(probes, chosen), "probes")


def result_counts(stops: StopIndex, endpoints: EndpointIndex, queries: DataFrame, need: int, method: str = "split", points: bool = True, **options) -> DataFrame:
    """``(query_id, transition_id, side, nearer)`` by filter, prune and verify, for all queries in one plan."""
    sides = filtered_probes(stops, queries, need, method, **options)
    left = prune_endpoints(endpoints, sides, need, route_shapes(stops) if method == "cell" else None, points, stops)
    counts = nearer_counts(left, stops, sides, need)
    return counts.filter(F.col("nearer") < need).join(few(sides.select("probe_id", "query_id"), PROBES), "probe_id").select("query_id", "transition_id", "side", "nearer")


def reverse_routes(route_points: DataFrame | StopIndex, endpoints: DataFrame | EndpointIndex, queries: DataFrame, k: int, mode: str = "any", rank_rule: str = "exact", method: str = "split", **options) -> DataFrame:
    """``(query_id, transition_id, mask)`` of ``queries(query_id, q_idx, x_m, y_m, exclude_route_id)``.

    Each side may be given as rows or as an index built before. With k of at least the number of routes, or no routes, every
    transition is in the result. ``exclude_route_id`` takes an existing route out of the competition.
    """
    if method not in METHODS:
        raise ValueError(f"method {method!r}")
    need = _need(k, rank_rule)
    if method in ("forward", "scan"):
        rows = endpoints.points if isinstance(endpoints, EndpointIndex) else endpoints
        routes = route_points.points().select("stop_id", "x_m", "y_m", F.explode("routes").alias("route_id")) if isinstance(route_points, StopIndex) else route_points
        return apply_mode(_exhaustive(routes, rows, queries, need, method == "forward"), mode)
    stops = route_points if isinstance(route_points, StopIndex) else build_stop_index(route_points)
    index = endpoints if isinstance(endpoints, EndpointIndex) else build_endpoint_index(endpoints)
    return apply_mode(result_counts(stops, index, queries, need, method, **options), mode)
