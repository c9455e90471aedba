"""Transitions as a stream: arrivals paired per user, counted in windows, deduplicated, classified for registered queries.

A new transition is classified once, by the routes alone, so results only grow until transitions expire.

Defined cases: a stream without rows gives no rows; repeated events count once where deduplicated, else each time; rows later than the
watermark are dropped from windows and sessions.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.reverse import reverse_routes
from ..plans.layout import StopIndex
from ..plans.shared import scratch_path


def stream_table(spark: SparkSession, folder: str, name: str, files_per_batch: int = 1) -> DataFrame:
    """One of the tables of a folder as a file stream."""
    schema = spark.read.parquet(f"{folder}/{name}.parquet").schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).option("pathGlobFilter", f"{name}.parquet").parquet(folder)


def pair_checkins(events: DataFrame, ttl_s: int | None = None, late: str = "1 hour") -> DataFrame:
    """``events(event_id, user_id, ts, x, y)`` to transitions: each check-in paired with its user's last one, kept as state.

    With ``ttl_s`` a check-in more than so many seconds after the last one starts anew, and state that old is dropped once the watermark
    (``late`` behind the latest check-in) has passed it. A check-in older than its user's last one comes too late and pairs with nothing.
    """

    def run(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        last = state.get if state.exists else None
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        out = []
        for e in rows.itertuples():
            at = e.ts.value // 1000
            if last is not None and at < last[2]:
                continue
            if last is not None and (ttl_s is None or at - last[2] <= ttl_s * 1_000_000):
                out.append((e.event_id, key[0], last[0], last[1], e.x, e.y, e.ts))
            last = (int(e.x), int(e.y), at)
        state.update(last)
        if ttl_s is not None:
            state.setTimeoutTimestamp(max(last[2] // 1000 + ttl_s * 1000, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame(out, columns=["transition_id", "user_id", "o_x", "o_y", "d_x", "d_y", "ts"])

    if ttl_s is not None:
        events = events.withWatermark("ts", late)
    out = "transition_id bigint, user_id bigint, o_x bigint, o_y bigint, d_x bigint, d_y bigint, ts timestamp"
    timeout = GroupStateTimeout.NoTimeout if ttl_s is None else GroupStateTimeout.EventTimeTimeout
    return events.groupBy("user_id").applyInPandasWithState(run, out, "x bigint, y bigint, at bigint", "append", timeout)


def window_counts(transitions: DataFrame, width: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    return transitions.withWatermark("ts", late).groupBy(F.window("ts", width, slide)).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")


def session_counts(events: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count("*").alias("n")).select("user_id", F.col("s.start").alias("start"), "n")


def deduplicated(events: DataFrame, key: str = "event_id", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def drained(stream: DataFrame, label: str, mode: str = "append", each: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """Runs a stream over what is there now and returns its rows: appended per batch, or the last state in ``complete`` mode.

    Batches are written by number, so a batch that runs again after a failure replaces its own rows.
    """
    spark = stream.sparkSession
    root = scratch_path(spark, label)

    def put(batch: DataFrame, n: int) -> None:
        rows = each(batch) if each else batch
        rows.write.mode("overwrite").parquet(f"{root}/rows/batch={n if mode == 'append' else 0}")

    q = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).foreachBatch(put).start()
    q.awaitTermination()
    return spark.read.parquet(f"{root}/rows").drop("batch")


def classify(transitions: DataFrame, stops: StopIndex, queries: DataFrame, k: int, mode: str = "any") -> DataFrame:
    """Each arriving transition held against the registered queries."""
    from ..schema import endpoints

    return drained(transitions, "stream-reverse", each=lambda batch: reverse_routes(stops, endpoints(batch), queries, k, mode))
