"""Query workloads: generated queries, existing routes as queries, planning queries."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _draw(seed: int, *parts: object) -> Column:
    """A repeatable number from 0 to 999,999."""
    return F.pmod(F.xxhash64(F.lit(seed), *[p if not isinstance(p, (int, str)) else F.lit(p) for p in parts]), F.lit(1_000_000))


def random_queries(route_points: DataFrame, n: int, length: int = 5, interval_m: int = 3000, seed: int = 1) -> DataFrame:
    """``n`` queries of ``length`` points from stops drawn by hash, each step ``interval_m`` long and turning by at most 90 degrees."""
    starts = route_points.select("stop_id", "x_m", "y_m").distinct().orderBy(_draw(seed, F.col("stop_id")), "stop_id").limit(n)
    first = starts.withColumn("heading", _draw(seed, "heading", F.col("stop_id")) * (2 * 3.141592653589793 / 1_000_000))
    turns = F.transform(F.sequence(F.lit(1), F.lit(length - 1)), lambda i: F.struct(i.alias("i"), ((F.pmod(F.xxhash64(F.lit(seed), i, F.col("stop_id")), F.lit(1_000_000)) / 1_000_000 - 0.5) * 3.141592653589793).alias("turn")))
    start = F.struct(F.col("heading").alias("h"), F.array(F.struct(F.lit(0).alias("q_idx"), F.col("x_m").alias("x_m"), F.col("y_m").alias("y_m"))).alias("out"))

    def step(acc: Column, t: Column) -> Column:
        h = acc["h"] + t["turn"]
        last = F.element_at(acc["out"], -1)
        new = F.struct(t["i"].alias("q_idx"), (last["x_m"] + F.round(F.cos(h) * interval_m).cast("bigint")).alias("x_m"), (last["y_m"] + F.round(F.sin(h) * interval_m).cast("bigint")).alias("y_m"))
        return F.struct(h.alias("h"), F.concat(acc["out"], F.array(new)).alias("out"))

    walked = first.withColumn("points", F.aggregate(turns, start, step, lambda acc: acc["out"])) if length > 1 else first.withColumn("points", start["out"])
    return walked.select(F.col("stop_id").alias("query_id"), F.explode("points").alias("p")).select("query_id", "p.*", F.lit(None).cast("bigint").alias("exclude_route_id"))


def route_queries(route_points: DataFrame, every: int = 1) -> DataFrame:
    """Every route as a query by each ``every``-th of its stops, taken out of the competition itself."""
    return route_points.filter((F.col("seq") - 1) % every == 0).select(F.col("route_id").alias("query_id"), F.col("seq").alias("q_idx"), "x_m", "y_m", F.col("route_id").alias("exclude_route_id"))


def planning_queries(route_points: DataFrame, stops: int = 5, percent: int = 140) -> DataFrame:
    """``(query_id, src, dst, max_len_m)``: the first and the ``stops``-th stop of each route, and a limit of so many percent of the
    route's length between them."""
    from ..operators.graph import segments

    ends = route_points.groupBy("route_id").agg(F.max(F.when(F.col("seq") == 1, F.col("stop_id"))).alias("src"), F.max(F.when(F.col("seq") == stops, F.col("stop_id"))).alias("dst"))
    length = segments(route_points).filter(F.col("seq") < stops).groupBy("route_id").agg(F.sum("length_m").alias("n"))
    return ends.join(length, "route_id").select(F.col("route_id").alias("query_id"), "src", "dst", F.expr(f"n * {percent} div 100").alias("max_len_m"))


def chord_queries(stops: DataFrame, edges: DataFrame, chord_m: int, n: int = 20) -> DataFrame:
    """``(query_id, src, dst, chord_m)``: ``n`` stops drawn by hash as starts, each with the stop whose straight distance is nearest to
    ``chord_m``, smaller ids first; both ends have edges."""
    places = stops.join(edges.select(F.col("src").alias("stop_id")).distinct(), "stop_id", "left_semi")
    first = places.orderBy(_draw(3, F.col("stop_id")), "stop_id").limit(n).select(F.col("stop_id").alias("src"), F.col("x_m").alias("sx"), F.col("y_m").alias("sy"))
    apart = F.sqrt(((F.col("sx") - F.col("x_m")) ** 2 + (F.col("sy") - F.col("y_m")) ** 2).cast("double"))
    near = places.join(F.broadcast(first), (F.abs(F.col("x_m") - F.col("sx")) <= 2 * chord_m) & (F.abs(F.col("y_m") - F.col("sy")) <= 2 * chord_m) & (F.col("stop_id") != F.col("src")))
    best = near.groupBy("src").agg(F.min(F.struct(F.abs(apart - chord_m).alias("gap"), F.col("stop_id").alias("dst"), F.round(apart).cast("bigint").alias("chord_m"))).alias("b"))
    return best.select(F.col("src").alias("query_id"), "src", "b.dst", "b.chord_m")
