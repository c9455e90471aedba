"""Schemas of the engine's tables. Coordinates are whole metres; distances are compared as squared 64-bit integers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Largest coordinate: squared distances and half-plane forms then stay within 64 bits.
LIMIT_M = 500_000_000

_TYPES = {"BIGINT": T.LongType(), "INT": T.IntegerType(), "STRING": T.StringType(), "TIMESTAMP": T.TimestampType()}


def _struct(ddl: str) -> T.StructType:
    """A schema from ``name TYPE, ...``, without a session."""
    return T.StructType([T.StructField(name, _TYPES[kind]) for name, kind in (part.split() for part in ddl.split(", "))])


ROUTE_POINTS = _struct("route_id BIGINT, seq INT, stop_id BIGINT, x_m BIGINT, y_m BIGINT")
TRANSITIONS = _struct("transition_id BIGINT, user_id BIGINT, o_x BIGINT, o_y BIGINT, d_x BIGINT, d_y BIGINT, ts TIMESTAMP")
ENDPOINTS = _struct("transition_id BIGINT, side STRING, x_m BIGINT, y_m BIGINT, ts TIMESTAMP")
QUERY_POINTS = _struct("query_id BIGINT, q_idx INT, x_m BIGINT, y_m BIGINT, exclude_route_id BIGINT")
EDGES = _struct("src BIGINT, dst BIGINT, length_m BIGINT")
RESULT = _struct("query_id BIGINT, transition_id BIGINT, mask INT")


def endpoints(transitions: DataFrame) -> DataFrame:
    """Two rows per transition: side ``o`` and side ``d``."""
    both = F.array(
        F.struct(F.lit("o").alias("side"), F.col("o_x").alias("x_m"), F.col("o_y").alias("y_m")),
        F.struct(F.lit("d").alias("side"), F.col("d_x").alias("x_m"), F.col("d_y").alias("y_m")),
    )
    kept = ["transition_id", *(["ts"] if "ts" in transitions.columns else [])]
    return transitions.select(*kept, F.explode(both).alias("p")).select("transition_id", "p.side", "p.x_m", "p.y_m", *kept[1:])


def checked_coordinates(df: DataFrame, *names: str) -> DataFrame:
    """``df``, failing at run time on a null or too large coordinate."""
    for name in names:
        bad = F.col(name).isNull() | (F.abs(name) > LIMIT_M)
        df = df.withColumn(name, F.when(bad, F.raise_error(F.concat(F.lit(f"{name} out of range: "), F.coalesce(F.col(name).cast("string"), F.lit("null"))))).otherwise(F.col(name)).cast("bigint"))
    return df
