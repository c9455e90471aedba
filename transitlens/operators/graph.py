"""The network that routes form, and distances in it."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.geometry import edge_length
from ..plans.shared import written


def segments(route_points: DataFrame) -> DataFrame:
    """Consecutive stops of each route with the length between them."""
    w = Window.partitionBy("route_id").orderBy("seq")
    nxt = F.lead(F.struct("stop_id", "x_m", "y_m")).over(w)
    rows = route_points.withColumn("n", nxt).filter("n IS NOT NULL")
    return rows.select("route_id", "seq", F.col("stop_id").alias("src"), F.col("n.stop_id").alias("dst"), edge_length(F.col("x_m"), F.col("y_m"), F.col("n.x_m"), F.col("n.y_m")).alias("length_m"))


def build(route_points: DataFrame, directed: bool = False) -> DataFrame:
    """``edges(src, dst, length_m)`` between different stops; undirected ones are listed both ways."""
    found = segments(route_points).filter("src <> dst").groupBy("src", "dst").agg(F.min("length_m").alias("length_m"))
    if directed:
        return found
    # Turned round only here: many routes share an edge, and each of their segments is shuffled once.
    ways = F.explode(F.array(*(F.struct(F.col(a).alias("src"), F.col(b).alias("dst"), "length_m") for a, b in (("src", "dst"), ("dst", "src"))))).alias("e")
    return found.select(ways).select("e.*").groupBy("src", "dst").agg(F.min("length_m").alias("length_m"))


def path_length(route_points: DataFrame) -> DataFrame:
    """``(route_id, length_m, n_stops)``: travel distance of each route."""
    lengths = segments(route_points).groupBy("route_id").agg(F.sum("length_m").alias("length_m"))
    stops = route_points.groupBy("route_id").agg(F.count("*").alias("n_stops"))
    return stops.join(lengths, "route_id", "left").select("route_id", F.coalesce("length_m", F.lit(0)).alias("length_m"), "n_stops")


def shortest_to(edges: DataFrame, targets: DataFrame, cap: int) -> DataFrame:
    """``(target, src, length_m)`` of all stops within ``cap`` of each of ``targets(target)``.

    Each round relaxes the edges into stops whose distance fell in the last one; a round's tables are written, so lineage stays short.
    """
    back = edges.select(F.col("dst").alias("at"), F.col("src").alias("to"), F.col("length_m").alias("step"))
    back = written(back, "edges-back")
    best = written(targets.select("target", F.col("target").alias("src"), F.lit(0).cast("bigint").alias("length_m"), F.lit(True).alias("fell")), "shortest")
    while not (front := best.filter("fell")).isEmpty():
        step = front.join(back, front["src"] == back["at"]).select("target", F.col("to").alias("src"), (F.col("length_m") + F.col("step")).alias("length_m")).filter(F.col("length_m") <= cap)
        both = best.select("target", "src", F.col("length_m").alias("old"), F.lit(None).cast("bigint").alias("new")).unionByName(step.select("target", "src", F.lit(None).cast("bigint").alias("old"), F.col("length_m").alias("new")))
        both = both.groupBy("target", "src").agg(F.min("old").alias("old"), F.min("new").alias("new"))
        fell = F.col("new").isNotNull() & (F.col("old").isNull() | (F.col("new") < F.col("old")))
        best = written(both.select("target", "src", F.least("old", "new").alias("length_m"), fell.alias("fell")), "shortest")
    return best.select("target", "src", "length_m")


def all_pairs(edges: DataFrame, cap: int | None = None) -> DataFrame:
    """Distances between all stops, by relaxing from every stop at once; ``cap`` keeps the table near-linear."""
    stops = edges.select(F.col("src").alias("target")).distinct()
    return shortest_to(edges, stops, cap if cap is not None else 1 << 60)
