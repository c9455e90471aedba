"""Shared helpers of the corpus operators: written tables, Arrow batch slices, joins to small tables."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.shared import scratch_path, written  # noqa: F401

#: Characters that end a word: space and the controls U+0009 to U+000D.
WORD = r"[^\x20\x09-\x0D]+"


def drop_written(df: DataFrame) -> None:
    """Deletes the files behind a table of :func:`written` that no later plan reads."""
    spark = df.sparkSession
    jvm = spark.sparkContext._jvm
    conf = spark.sparkContext._jsc.hadoopConfiguration()
    for f in {x.rsplit("/", 1)[0] for x in df.inputFiles()}:
        path = jvm.org.apache.hadoop.fs.Path(f)
        path.getFileSystem(conf).delete(path, True)


def text_or_empty(name: str = "text") -> Column:
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def slices(texts: pa.Array, limit: int = 1 << 20) -> Iterator[tuple[int, int, list[str]]]:
    """Ranges of a batch's texts, about ``limit`` bytes each and one text at least: bounds memory whatever a batch holds."""
    ends = np.cumsum(pc.binary_length(texts).to_numpy(zero_copy_only=False).astype(np.int64)) if len(texts) else np.zeros(0, np.int64)
    lo = done = 0
    while lo < len(texts):
        hi = max(lo + 1, int(np.searchsorted(ends, done + limit, side="right")))
        yield lo, hi, texts.slice(lo, hi - lo).to_pylist()
        lo, done = hi, int(ends[hi - 1])


#: A table of at most so many rows of a key and a few numbers is broadcast; above, Spark shuffles and splits skewed partitions.
BROADCAST_ROWS = 100_000


def join_hosts(rows: DataFrame, table: DataFrame, key: str, how: str = "inner") -> DataFrame:
    """``rows`` joined null-safe to ``table``, a written table with a row per key; broadcast only where its counted rows are few."""
    right = table.withColumnRenamed(key, "_key")
    if table.count() <= BROADCAST_ROWS:
        right = F.broadcast(right)
    return rows.join(right, rows[key].eqNullSafe(right["_key"]), how).drop("_key")
