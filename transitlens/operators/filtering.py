"""Choosing the stops that prune, and the test whether they rule out a box.

A probe is what is pruned for: a query, or one of its points. All probes go through one plan; nothing loops over queries.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import geometry as G
from ..functions.clip import with_inside
from ..plans.layout import StopIndex
from ..plans.shared import few

#: Stops that a probe prunes with at first, dealt to the eight directions around it; any subset gives right results.
SEEDS, SECTORS = 64, 8
#: Probes with their stops, and cells of the widest level, up to which a table of them is broadcast; above, Spark shuffles.
PROBES, TOP_CELLS = 2_000, 10_000


def _without(routes: Column, excluded: Column) -> Column:
    return F.filter(routes, lambda r: excluded.isNull() | (r != excluded))


def seed_stops(index: StopIndex, probes: DataFrame, order: str = "distance", seeds: int = SEEDS, credit: str = "crossover") -> DataFrame:
    """``(probe_id, stop_id, x_m, y_m, routes)``: stops around each point of a probe, nearest or most covered first in each direction.

    A probe of one point takes ``seeds`` stops; one of many points a share of them around each point, one a direction at least.
    Candidates come from the cells around the points by an equi-join, so no stop far from a probe is looked at.
    """
    level = 12
    offsets = [(dx, dy) for dx in (-1, 0, 1) for dy in (-1, 0, 1)]
    at = probes.select("probe_id", "exclude_route_id", "q", F.explode("q").alias("p"))
    cells = at.select("probe_id", "exclude_route_id", "q", F.explode(F.array(*(G.grid_cell(G.grid(F.col("p.x_m"), level) + dx, G.grid(F.col("p.y_m"), level) + dy) for dx, dy in offsets))).alias("cell")).distinct()
    near = cells.join(index.stops.filter(F.col("level") == level), "cell")
    near = near.withColumn("routes", _without(F.col("routes"), F.col("exclude_route_id"))).filter(F.size("routes") > 0)
    x, y = F.col("x_m"), F.col("y_m")
    nearest = F.array_min(F.transform("q", lambda q, i: F.struct(G.sq_dist(x, y, q["x_m"], q["y_m"]).alias("d2"), i.alias("i"))))
    near = near.withColumn("_n", nearest).withColumns({"d2": F.col("_n.d2"), "_q": F.get("q", F.col("_n.i"))}).filter("d2 > 0")
    sector = F.floor((F.atan2((y - F.col("_q.y_m")).cast("double"), (x - F.col("_q.x_m")).cast("double")) + 3.14159265358979) / 6.2831853071796 * SECTORS)
    by = [F.desc(F.size("routes")), "d2", "stop_id"] if order == "coverage" else ["d2", "stop_id"]
    w = Window.partitionBy("probe_id", "_n.i", sector).orderBy(*by)
    share = F.greatest(F.lit(1), F.floor(F.lit(seeds // SECTORS) / F.size("q")))
    picked = near.withColumn("nth", F.row_number().over(w)).filter(F.col("nth") <= share)
    routes = F.col("routes") if credit == "crossover" else F.slice("routes", 1, 1)
    return picked.select("probe_id", "stop_id", "x_m", "y_m", routes.alias("routes"))


def with_stops(probes: DataFrame, stops: DataFrame) -> DataFrame:
    """``probes`` with the stops each prunes with as an array, empty without any; a bounded number, so a probe stays one small row."""
    listed = stops.groupBy("probe_id").agg(F.collect_list(F.struct("x_m", "y_m", "routes")).alias("stops"))
    return probes.join(listed, "probe_id", "left").withColumn("stops", F.coalesce("stops", F.array().cast("array<struct<x_m bigint, y_m bigint, routes array<bigint>>>")))


def routes_around(box: Column, stops: Column, query: Column) -> Column:
    """Distinct routes of those stops whose filter space holds the box."""
    holding = F.filter(stops, lambda s: G.inside_filter_space(box, s["x_m"], s["y_m"], query))
    return F.array_distinct(F.flatten(F.transform(holding, lambda s: s["routes"])))


def point_box(x: Column, y: Column) -> Column:
    return F.struct(x.alias("x_lo"), x.alias("x_hi"), y.alias("y_lo"), y.alias("y_hi"))


def _tested(boxes: DataFrame, probes: DataFrame, need: int, routes: DataFrame | None) -> DataFrame:
    """``boxes(probe_id, level, cell, box)`` with ``out``: whether enough routes rule the box out.

    With ``routes``, whole routes count as well: those with a stop among the probe's, where no single stop has counted them.
    """
    sides = few(probes.select("probe_id", "q", "stops"), PROBES)
    state = boxes.join(sides, "probe_id").withColumn("by", routes_around(F.col("box"), F.col("stops"), F.col("q")))
    if routes is None:
        return state.select(*boxes.columns, (F.size("by") >= need).alias("out"))
    known = F.array_distinct(F.flatten(F.transform("stops", lambda s: s["routes"])))
    # Any subset of the routes prunes soundly; so many at most are tried for a box.
    rest = F.when(F.size("by") < need, F.slice(F.array_except(known, "by"), 1, 4 * need))
    pairs = state.select(*boxes.columns, "q", F.size("by").alias("n"), F.explode_outer(rest).alias("route_id")).join(routes, "route_id", "left")
    # A box whose corners are not all nearer to the route cannot be inside its space; the clipping sees the others only.
    maybe = F.col("route").isNotNull()
    for x in ("box.x_lo", "box.x_hi"):
        for y in ("box.y_lo", "box.y_hi"):
            maybe = maybe & G.in_route_space(F.col(x), F.col(y), F.col("route"), F.col("q"))
    tried = with_inside(pairs.withColumn("maybe", F.coalesce(maybe, F.lit(False))))
    out = F.max("n") + F.sum(F.col("inside").cast("int")) >= need
    return tried.groupBy("probe_id", "level", "cell").agg(F.first("box").alias("box"), out.alias("out"))


def descend(cells: DataFrame, probes: DataFrame, need: int, routes: DataFrame | None = None, also: Callable[[DataFrame], DataFrame] | None = None) -> tuple[DataFrame, DataFrame]:
    """Live leaf cells and pruned cells of each probe, from the coarsest level down; a pruned cell's children are never looked at.

    ``also`` may leave out more of a level's live cells, as pruned.
    """
    live, pruned = None, None
    for level in G.DESCENT:
        here = cells.filter(F.col("level") == level).select("level", "cell", "box")
        if live is None:
            # The widest cells of a plane are few: each probe starts at all of them.
            boxes = probes.select("probe_id").join(few(here, TOP_CELLS))
        else:
            up = G.DESCENT[G.DESCENT.index(level) - 1]
            parents = live.select("probe_id", F.col("cell").alias("parent"))
            boxes = here.withColumn("parent", G.parent_cell(F.col("cell"), up - level)).join(parents, "parent").drop("parent")
        tested = _tested(boxes.select("probe_id", "level", "cell", "box"), probes, need, routes)
        live = tested.filter("NOT out").drop("out")
        gone = tested.filter("out").drop("out")
        if also is not None:
            live = also(live)
        pruned = gone if pruned is None else pruned.unionByName(gone)
    return live, pruned


def route_shapes(index: StopIndex) -> DataFrame:
    """``(route_id, route)``, each route's stops as an array."""
    return index.points().select(F.explode("routes").alias("route_id"), F.struct("x_m", "y_m").alias("p")).groupBy("route_id").agg(F.collect_list("p").alias("route"))


def choose_filter_stops(index: StopIndex, probes: DataFrame, need: int, test_points: bool = True, credit: str = "crossover", order: str = "distance", whole_route: bool = False, seeds: int = SEEDS) -> tuple[DataFrame, DataFrame, DataFrame]:
    """``(filter_stops, pruned_cells, pruned_points)`` of each probe; every stop of the index is in exactly one of them.

    Seeds prune the route cells level by level; stops of live leaf cells join the seeds unless they are pruned themselves
    (``test_points``).
    """
    sides = with_stops(probes, seed_stops(index, probes, order, seeds, credit))
    live, pruned = descend(index.cells, sides, need, route_shapes(index) if whole_route else None)
    rest = index.points().join(live.select("probe_id", "cell"), "cell").join(few(sides, PROBES), "probe_id")
    rest = rest.withColumn("routes", _without(F.col("routes"), F.col("exclude_route_id"))).filter(F.size("routes") > 0)
    if credit == "single":
        rest = rest.withColumn("routes", F.slice("routes", 1, 1))
    out = F.size(routes_around(point_box(F.col("x_m"), F.col("y_m")), F.col("stops"), F.col("q"))) >= need if test_points else F.lit(False)
    rest = rest.select("probe_id", "stop_id", "x_m", "y_m", "routes", out.alias("out"))
    return rest.filter("NOT out").drop("out"), pruned, rest.filter("out").drop("out")
