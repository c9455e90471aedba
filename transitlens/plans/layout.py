"""Indexes as tables: stops and cells of the routes, endpoints and cells of the transitions, and their updates.

A cell directory stands for a spatial tree: grid cells at fixed levels, each with the tight box of what it holds. Route cells
also carry the routes with a stop inside. Stored endpoints are partitioned by day and clustered by cell, coarse to fine, so a query that knows its
live cells reads the row groups of those cells only.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.geometry import DESCENT, LEVELS, cell_at
from .shared import written


def _box() -> Column:
    return F.struct(F.min("x_m").alias("x_lo"), F.max("x_m").alias("x_hi"), F.min("y_m").alias("y_lo"), F.max("y_m").alias("y_hi"))


def stop_routes(route_points: DataFrame) -> DataFrame:
    """A row per distinct stop with the sorted routes through it."""
    return (
        route_points.groupBy("stop_id")
        .agg(F.min("x_m").alias("x_m"), F.min("y_m").alias("y_m"), F.array_sort(F.collect_set("route_id")).alias("routes"))
        .withColumn("n_routes", F.size("routes"))
    )


def _by_level(points: DataFrame, levels: tuple[int, ...]) -> DataFrame:
    """``points`` once for each level, with ``level`` and ``cell``."""
    at = F.explode(F.array(*(F.struct(F.lit(s).alias("level"), cell_at(F.col("x_m"), F.col("y_m"), s).alias("cell")) for s in levels)))
    return points.withColumn("_at", at).select("*", "_at.level", "_at.cell").drop("_at")


def cell_routes(stops: DataFrame, levels: tuple[int, ...] = LEVELS) -> DataFrame:
    """``(level, cell, box, routes)``: the routes with a stop in each cell."""
    return _by_level(stops, levels).groupBy("level", "cell").agg(_box().alias("box"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("routes")))).alias("routes"))


@dataclass(frozen=True)
class StopIndex:
    """The route side, as written tables so that plans over it stay short: ``base`` (a row per stop: coordinates, routes), ``stops`` (a row
    per stop and level, with level and cell) and ``cells``; the last two are written when first asked for."""

    base: DataFrame

    @cached_property
    def stops(self) -> DataFrame:
        return written(_by_level(self.base, LEVELS), "stop-levels")

    @cached_property
    def cells(self) -> DataFrame:
        return written(cell_routes(self.base), "stop-cells")

    def points(self) -> DataFrame:
        """A row per stop, with its cell of the finest level."""
        return self.base.withColumn("cell", cell_at(F.col("x_m"), F.col("y_m"), DESCENT[-1]))


def build_stop_index(route_points: DataFrame) -> StopIndex:
    return StopIndex(written(stop_routes(route_points), "stops"))


@dataclass(frozen=True)
class EndpointIndex:
    """The transition side: ``points`` with ``cell`` (finest level) and the directory ``cells(level, cell, box, n)``, written when first
    asked for unless a stored one is given."""

    points: DataFrame
    stored: DataFrame | None = None

    @cached_property
    def cells(self) -> DataFrame:
        return written(endpoint_cells(self.points.drop("cell")), "endpoint-cells") if self.stored is None else self.stored


def endpoint_cells(endpoints: DataFrame, levels: tuple[int, ...] = DESCENT) -> DataFrame:
    return _by_level(endpoints, levels).groupBy("level", "cell").agg(_box().alias("box"), F.count("*").alias("n"))


def build_endpoint_index(endpoints: DataFrame, cells: DataFrame | None = None) -> EndpointIndex:
    """An index over ``endpoints``; ``cells`` may be a stored directory."""
    points = endpoints if "cell" in endpoints.columns else endpoints.withColumn("cell", cell_at(F.col("x_m"), F.col("y_m"), DESCENT[-1]))
    return EndpointIndex(points, cells)


def write_endpoints(endpoints: DataFrame, path: str, mode: str = "errorifexists") -> None:
    """Stores endpoints by day, clustered by cell, and appends their directory rows; appending needs no rebuild."""
    coded = endpoints.withColumns({"day": F.to_date("ts"), "cell": cell_at(F.col("x_m"), F.col("y_m"), DESCENT[-1])})
    order = ["day", *(cell_at(F.col("x_m"), F.col("y_m"), s) for s in DESCENT)]
    coded.repartitionByRange(*order).sortWithinPartitions(*order).write.partitionBy("day").mode(mode).parquet(f"{path}/points")
    _by_level(coded.drop("cell"), DESCENT).groupBy("day", "level", "cell").agg(_box().alias("box"), F.count("*").alias("n")).write.partitionBy("day").mode(mode).parquet(f"{path}/cells")


def append_transitions(endpoints: DataFrame, path: str) -> None:
    write_endpoints(endpoints, path, "append")


def read_endpoints(spark: SparkSession, path: str, since: str | None = None, before: str | None = None) -> EndpointIndex:
    """The stored index, of the days from ``since`` to before ``before``; partitions outside are not read."""
    points, cells = spark.read.parquet(f"{path}/points"), spark.read.parquet(f"{path}/cells")
    for op, day in ((">=", since), ("<", before)):
        if day is not None:
            points, cells = (x.filter(f"day {op} DATE'{day}'") for x in (points, cells))
    box = F.struct(F.min("box.x_lo").alias("x_lo"), F.max("box.x_hi").alias("x_hi"), F.min("box.y_lo").alias("y_lo"), F.max("box.y_hi").alias("y_hi"))
    return EndpointIndex(points, cells.groupBy("level", "cell").agg(box.alias("box"), F.sum("n").alias("n")))


def expire(spark: SparkSession, path: str, before: str) -> int:
    """Deletes the partitions of days before ``before``; returns how many."""
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    gone = 0
    for part in ("points", "cells"):
        root = jvm.org.apache.hadoop.fs.Path(f"{path}/{part}")
        fs = root.getFileSystem(conf)
        for status in fs.listStatus(root):
            name = status.getPath().getName()
            if name.startswith("day=") and name[4:] < before:
                fs.delete(status.getPath(), True)
                gone += part == "points"
    return gone


def append_routes(route_points: DataFrame, new: DataFrame) -> DataFrame:
    """The route side is small: new routes are added and the index is built again."""
    return route_points.unionByName(new)


def remove_routes(route_points: DataFrame, ids: list[int]) -> DataFrame:
    return route_points.filter(~F.col("route_id").isin(ids))
