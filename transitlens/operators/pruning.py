"""Dropping transition endpoints that enough routes are nearer to than the query."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import geometry as G
from ..plans.layout import EndpointIndex, StopIndex
from ..plans.shared import few, written
from .filtering import PROBES, descend, point_box, routes_around
from .lone import by_ids, opened, prune_by_tiles
from .verify import level_for

#: Live cells up to which a table of them is broadcast.
LIVE_CELLS = 200_000
#: Least distance to the query, in metres, of a cell that is held against the routes around it.
FAR_M = 4096


def crowded_boxes(live: DataFrame, stops: StopIndex, probes: DataFrame, need: int) -> DataFrame:
    """``(probe_id, cell)`` of those of ``live(probe_id, cell, box)`` around which enough routes have a stop that is nearer to every
    point of the box than the query is, told by route cells wholly that near; at most ``need`` routes of each cell."""
    rows = live.join(few(probes.select("probe_id", "q", "exclude_route_id"), PROBES), "probe_id")
    rows = rows.withColumn("r2", G.box_min_sq(F.col("box"), F.col("q"))).drop("q").filter(F.col("r2") >= FAR_M * FAR_M)
    r = F.floor(F.sqrt(F.col("r2").cast("double")))
    rows = rows.withColumn("level", level_for(r, 0.25))
    for axis in "xy":
        ends = [G.grid(F.col(f"box.{axis}_{end}") + sign * r, F.col("level")) for end, sign in (("hi", -1), ("lo", 1))]
        rows = rows.withColumn(f"g{axis}", F.explode(F.sequence(F.least(*ends), F.greatest(*ends))))
    rows = rows.select("probe_id", F.col("cell").alias("leaf"), F.col("box").alias("leaf_box"), "r2", "exclude_route_id", "level", G.grid_cell(F.col("gx"), F.col("gy")).alias("cell"))
    met = rows.join(stops.cells, ["level", "cell"]).filter(G.boxes_max_sq(F.col("leaf_box"), F.col("box")) < F.col("r2"))
    some = F.slice(F.filter("routes", lambda x: F.col("exclude_route_id").isNull() | (x != F.col("exclude_route_id"))), 1, need)
    return met.groupBy("probe_id", F.col("leaf").alias("cell")).agg(F.size(F.array_distinct(F.flatten(F.collect_list(some)))).alias("n")).filter(F.col("n") >= need).select("probe_id", "cell")


def prune_endpoints(index: EndpointIndex, probes: DataFrame, need: int, routes: DataFrame | None = None, points: bool = True, stops: StopIndex | None = None) -> DataFrame:
    """``(probe_id, transition_id, side, x_m, y_m, dq)``: endpoints left, each with its squared distance to the whole query.

    The descent runs over the cell directory; with ``stops``, cells that it leaves far from the query are held against the routes
    around them, at each level. Endpoints are read for live leaf cells only, by a join on the cell. A probe of one query point keeps the endpoints that
    have it as their nearest query point: the others are decided there. Queries of one point each are pruned in tiles; only those that
    tiles leave open descend.
    """
    if by_ids(probes):
        found, probes = prune_by_tiles(index, stops, probes, need)
        probes = written(opened(stops, probes), "open-probes")
        return found if probes.isEmpty() else found.unionByName(_by_descent(index, probes, need, routes, points, stops))
    return _by_descent(index, probes, need, routes, points, stops)


def _by_descent(index: EndpointIndex, probes: DataFrame, need: int, routes: DataFrame | None, points: bool, stops: StopIndex | None) -> DataFrame:
    """:func:`prune_endpoints` through the cell directory."""

    def near(live: DataFrame) -> DataFrame:
        live = written(live, "live-cells")
        return written(live.join(crowded_boxes(live, stops, probes, need), ["probe_id", "cell"], "left_anti"), "live-cells")

    live, _ = descend(index.cells, probes, need, routes, near if stops is not None else None)
    live = live if stops is not None else written(live, "live-cells")
    # Each endpoint meets a query once and finds the point it is nearest to, then the one probe that this point is.
    asked = probes.select("query_id", "all_q").dropDuplicates(["query_id"])
    cells = live.select("probe_id", "cell").join(few(probes.select("probe_id", "query_id"), PROBES), "probe_id")
    found = index.points.join(few(cells.select("query_id", "cell").distinct(), LIVE_CELLS), "cell").join(few(asked, PROBES), "query_id")
    x, y = F.col("x_m"), F.col("y_m")
    near = F.array_min(F.transform("all_q", lambda p: F.struct(G.sq_dist(x, y, p["x_m"], p["y_m"]).alias("d"), p["q_idx"].alias("i"))))
    found = found.withColumn("near", near).drop("all_q")
    split = not probes.filter("q_idx IS NOT NULL").isEmpty()
    found = found.withColumn("at", F.col("near.i") if split else F.lit(-1))
    sides = few(probes.select("probe_id", "query_id", F.coalesce("q_idx", F.lit(-1)).alias("at"), "q", "stops"), PROBES)
    found = found.join(sides, ["query_id", "at"]).join(few(live.select("probe_id", "cell"), LIVE_CELLS), ["probe_id", "cell"], "left_semi")
    if points:
        found = found.filter(F.size(routes_around(point_box(x, y), F.col("stops"), F.col("q"))) < need)
    return found.select("probe_id", "transition_id", "side", "x_m", "y_m", F.col("near.d").alias("dq"))
