"""Exact counting of the routes strictly nearer to a candidate than the query is, in two rounds.

Defined cases: a candidate on a query point has no nearer route; a repeated candidate counts once; no candidates give no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import geometry as G
from ..plans.layout import StopIndex
from ..plans.shared import few, written
from .lone import NEAR_SQ, by_ids, nearer_by_tiles

#: Probes up to which a table of them is broadcast; above, Spark shuffles.
PROBES = 20_000
KEYS = ["probe_id", "transition_id", "side"]


def level_for(radius: Column, share: float) -> Column:
    """The finest level whose cells are at least ``share`` of the radius wide."""
    level = F.lit(G.LEVELS[-1])
    for s in reversed(G.LEVELS[:-1]):
        level = F.when(radius * share <= float(1 << s), F.lit(s)).otherwise(level)
    return level


def _cover(candidates: DataFrame, share: float) -> DataFrame:
    """Each candidate with the cells that its circle to the query touches."""
    rows = candidates.withColumn("radius", F.ceil(F.sqrt(F.col("dq").cast("double"))))
    rows = rows.withColumn("level", level_for(F.col("radius"), share))
    lo_x, hi_x = (G.grid(F.col("x_m") + d * F.col("radius"), F.col("level")) for d in (-1, 1))
    lo_y, hi_y = (G.grid(F.col("y_m") + d * F.col("radius"), F.col("level")) for d in (-1, 1))
    rows = rows.withColumn("gx", F.explode(F.sequence(lo_x, hi_x))).withColumn("gy", F.explode(F.sequence(lo_y, hi_y)))
    return rows.withColumn("cell", G.grid_cell(F.col("gx"), F.col("gy"))).drop("gx", "gy", "radius")


def _allowed(routes: Column, excluded: Column) -> Column:
    return F.filter(routes, lambda r: excluded.isNull() | (r != excluded))


def crowded(candidates: DataFrame, index: StopIndex, probes: DataFrame, need: int) -> DataFrame:
    """The keys of candidates that cells wholly nearer than the query rule out unopened, with at most ``need`` routes of each cell."""
    x, y, dq = F.col("x_m"), F.col("y_m"), F.col("dq")
    met = _cover(candidates.filter("dq > 0"), 0.25).join(index.cells, ["level", "cell"]).filter(G.point_box_max_sq(F.col("box"), x, y) < dq)
    met = met.join(few(probes.select("probe_id", "exclude_route_id"), PROBES), "probe_id")
    some = F.slice(_allowed(F.col("routes"), F.col("exclude_route_id")), 1, need)
    return met.groupBy(*KEYS).agg(F.size(F.array_distinct(F.flatten(F.collect_list(some)))).alias("n")).filter(F.col("n") >= need).select(*KEYS)


def nearer_counts(candidates: DataFrame, index: StopIndex, probes: DataFrame, need: int) -> DataFrame:
    """``(probe_id, transition_id, side, nearer)`` of those of ``candidates(probe_id, transition_id, side, x_m, y_m, dq)`` that the first
    round leaves.

    First, candidates with enough routes in cells wholly nearer are out. For the others a cell wholly nearer counts its routes unopened,
    one wholly farther counts nothing, and the rest are opened: their stops are measured. Joins are on cells, of a width that suits the
    candidate's distance, so none looks at more than a few hundred. Near candidates of queries of one point are counted in tiles.
    """
    candidates = written(candidates.dropDuplicates(KEYS), "candidates")
    if not by_ids(probes):
        return _in_rounds(candidates, index, probes, need)
    near, far = nearer_by_tiles(candidates.filter(F.col("dq") < NEAR_SQ), index), candidates.filter(F.col("dq") >= NEAR_SQ)
    return near if far.isEmpty() else near.unionByName(_in_rounds(far, index, probes, need))


def _in_rounds(candidates: DataFrame, index: StopIndex, probes: DataFrame, need: int) -> DataFrame:
    """:func:`nearer_counts` of distinct candidates through the cells."""
    left = written(candidates.join(crowded(candidates, index, probes, need), KEYS, "left_anti"), "undecided")
    met = _cover(left.filter("dq > 0"), 0.5).join(index.cells, ["level", "cell"])
    x, y, dq = F.col("x_m"), F.col("y_m"), F.col("dq")
    met = met.filter(G.point_box_min_sq(F.col("box"), x, y) < dq).withColumn("whole", G.point_box_max_sq(F.col("box"), x, y) < dq)
    whole = met.filter("whole").select(*KEYS, F.explode("routes").alias("route_id"))
    stops = index.stops.select("level", "cell", F.col("x_m").alias("sx"), F.col("y_m").alias("sy"), F.col("routes").alias("through"))
    opened = met.filter("NOT whole").select(*KEYS, "x_m", "y_m", "dq", "level", "cell").join(stops, ["level", "cell"]).filter(G.sq_dist(x, y, F.col("sx"), F.col("sy")) < dq)
    routes = whole.unionByName(opened.select(*KEYS, F.explode("through").alias("route_id"))).distinct()
    routes = routes.join(few(probes.select("probe_id", "exclude_route_id"), PROBES), "probe_id").filter("exclude_route_id IS NULL OR route_id <> exclude_route_id")
    counts = routes.groupBy(*KEYS).agg(F.count("*").alias("nearer"))
    return left.select(*KEYS).join(counts, KEYS, "left").withColumn("nearer", F.coalesce("nearer", F.lit(0)))
