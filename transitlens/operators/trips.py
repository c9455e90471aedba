"""Operators around the queries: stops near a point, boardings of routes, check-ins before a time, overlaps."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import geometry as G


def within_radius(points: DataFrame, stops: DataFrame, radius_m: int) -> DataFrame:
    """``points`` with each stop within the radius and its squared distance: a range join by cells at least as wide as the radius."""
    level = next((s for s in G.LEVELS if (1 << s) >= radius_m), None)
    if level is None:
        raise ValueError(f"radius {radius_m} is wider than the widest cell")
    x, y = F.col("x_m"), F.col("y_m")
    near = [(i, j) for i in (-1, 0, 1) for j in (-1, 0, 1)]
    cells = points.withColumn("cell", F.explode(F.array(*(G.grid_cell(G.grid(x, level) + i, G.grid(y, level) + j) for i, j in near))))
    side = stops.select("stop_id", F.col("x_m").alias("sx"), F.col("y_m").alias("sy"), G.cell_at(x, y, level).alias("cell"))
    d2 = G.sq_dist(x, y, F.col("sx"), F.col("sy"))
    return cells.join(side, "cell").withColumn("d2", d2).filter(F.col("d2") <= radius_m * radius_m).drop("cell", "sx", "sy")


def boardings(transitions: DataFrame, stops: DataFrame, radius_m: int = 2000) -> DataFrame:
    """``(transition_id, ts, route_id)``: the routes through the stop nearest to a transition's origin, within the radius."""
    origins = transitions.select("transition_id", "ts", F.col("o_x").alias("x_m"), F.col("o_y").alias("y_m"))
    near = within_radius(origins, stops, radius_m).groupBy("transition_id", "ts").agg(F.min(F.struct("d2", "stop_id"))["stop_id"].alias("stop_id"))
    return near.join(stops.select("stop_id", F.explode("routes").alias("route_id")), "stop_id").select("transition_id", "ts", "route_id")


def last_before(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """As-of join: ``left(key, at, ...)`` with the last ``value`` of ``right(key, at, value)`` at or before its time; one sort."""
    rows = left.withColumn("_l", F.struct(*left.columns)).select(key, at, "_l", F.lit(None).cast(right.schema[value].dataType).alias(value), F.lit(1).alias("_side"))
    seen = right.select(key, at, F.lit(None).cast(rows.schema["_l"].dataType).alias("_l"), value, F.lit(0).alias("_side"))
    w = Window.partitionBy(key).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return rows.unionByName(seen).withColumn(value, F.last(value, ignorenulls=True).over(w)).filter("_side = 1").select("_l.*", value)
