"""Measures: data set counts, lengths and ratios, histograms, running times, pruning power."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.filtering import route_shapes
from ..operators.graph import build, path_length
from ..operators.pruning import prune_endpoints
from ..operators.reverse import filtered_probes
from ..operators.verify import nearer_counts
from .layout import EndpointIndex, StopIndex
from .shared import written


def dataset_stats(route_points: DataFrame, transitions: DataFrame) -> DataFrame:
    """``(name, value)``: routes, stops, undirected edges, transitions, and the bounds of the plane."""
    side = route_points.agg(F.count_distinct("route_id").alias("routes"), F.count_distinct("stop_id").alias("stops"), F.min("x_m").alias("x_lo"), F.max("x_m").alias("x_hi"), F.min("y_m").alias("y_lo"), F.max("y_m").alias("y_hi"))
    edges = build(route_points).filter("src < dst").agg(F.count("*").alias("edges"))
    trips = transitions.agg(F.count("*").alias("transitions"))
    # One row each.
    one = side.crossJoin(edges).crossJoin(trips)
    return one.select(F.explode(F.array(*(F.struct(F.lit(c).alias("name"), F.col(c).cast("bigint").alias("value")) for c in one.columns))).alias("r")).select("r.*")


def detour_ratio(route_points: DataFrame) -> DataFrame:
    """``(route_id, length_m, n_stops, chord_m, interval_m, ratio)``; the ratio is null for a route that ends where it starts."""
    ends = route_points.groupBy("route_id").agg(F.min_by(F.struct("x_m", "y_m"), "seq").alias("a"), F.max_by(F.struct("x_m", "y_m"), "seq").alias("b"))
    chord = F.sqrt(((F.col("a.x_m") - F.col("b.x_m")) * (F.col("a.x_m") - F.col("b.x_m")) + (F.col("a.y_m") - F.col("b.y_m")) * (F.col("a.y_m") - F.col("b.y_m"))).cast("double"))
    rows = path_length(route_points).join(ends.select("route_id", chord.alias("chord")), "route_id")
    return rows.select("route_id", "length_m", "n_stops", F.round("chord", 6).alias("chord_m"), F.round(F.col("length_m") / F.col("n_stops"), 6).alias("interval_m"), F.round(F.when(F.col("chord") > 0, F.col("length_m") / F.col("chord")), 6).alias("ratio"))


def histogram(df: DataFrame, column: str, low: float, high: float, bins: int) -> DataFrame:
    """``(bin, n)``; values outside fall into bins 0 and ``bins + 1``, nulls into none."""
    return df.filter(F.col(column).isNotNull()).groupBy(F.width_bucket(F.col(column), F.lit(float(low)), F.lit(float(high)), F.lit(bins)).cast("bigint").alias("bin")).agg(F.count("*").alias("n"))


def timed(make: Callable[[], DataFrame], repeat: int = 1) -> dict[str, float]:
    """Seconds to run a plan into the noop sink: mean, median, 95th percentile."""
    took = []
    for _ in range(repeat):
        began = time.time()
        make().write.format("noop").mode("overwrite").save()
        took.append(time.time() - began)
    took.sort()
    return {"mean": sum(took) / len(took), "p50": took[len(took) // 2], "p95": took[min(len(took) - 1, int(0.95 * len(took)))]}


def phases(stops: StopIndex, endpoints: EndpointIndex, queries: DataFrame, k: int, method: str = "split") -> list[tuple[str, float, int]]:
    """``(phase, seconds, rows)`` of a reverse query: stops to prune with, candidates left by pruning, endpoints won."""
    out, began = [], time.time()

    def ended(phase: str, rows: int) -> None:
        nonlocal began
        out.append((phase, time.time() - began, rows))
        began = time.time()

    sides = filtered_probes(stops, queries, k, method)
    ended("filter", sides.agg(F.coalesce(F.sum(F.size("stops")), F.lit(0))).first()[0])
    left = written(prune_endpoints(endpoints, sides, k, route_shapes(stops) if method == "cell" else None, True, stops), "phase-candidates")
    ended("prune", left.count())
    ended("verify", written(nearer_counts(left, stops, sides, k).filter(F.col("nearer") < k), "phase-won").count())
    return out


def pruning_power(stops: StopIndex, endpoints: EndpointIndex, queries: DataFrame, k: int, method: str = "split") -> DataFrame:
    """``(probes, filter_stops, candidates, won)`` of a method: work that does not depend on the machine."""
    sides = filtered_probes(stops, queries, k, method)
    left = written(prune_endpoints(endpoints, sides, k, route_shapes(stops) if method == "cell" else None, True, stops), "power-candidates")
    won = nearer_counts(left, stops, sides, k).filter(F.col("nearer") < k)
    counts = [sides.agg(F.count("*").alias("probes"), F.sum(F.size("stops")).alias("filter_stops")), left.agg(F.count("*").alias("candidates")), won.agg(F.count("*").alias("won"))]
    # One row each.
    return counts[0].join(F.broadcast(counts[1])).join(F.broadcast(counts[2]))
