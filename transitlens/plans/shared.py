"""Tables written to the folder that driver and executors share, to end a loop's lineage."""

from __future__ import annotations

import atexit
import os
import shutil
import uuid
from collections.abc import Iterable, Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` where set; only a local master may do without."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    master = spark.sparkContext.master
    if not master.startswith("local") or master.startswith("local-cluster"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    own = f"/tmp/checkpoints/lens-{os.getpid()}"
    if not os.path.isdir(own):
        os.makedirs(own, exist_ok=True)
        atexit.register(shutil.rmtree, own, ignore_errors=True)
    return f"file://{own}"


def few(table: DataFrame, most: int) -> DataFrame:
    """``table``, broadcast only where its counted rows are at most so many."""
    return F.broadcast(table) if table.count() <= most else table


#: Paths of the tables written so far, by this process.
_PATHS: list[str] = []


def scratch_path(spark: SparkSession, label: str) -> str:
    """A fresh path in the shared folder; :func:`discard` deletes what lies there."""
    _PATHS.append(f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}")
    return _PATHS[-1]


#: Whether a statement's shuffle files are deleted at its end; otherwise they stay until the driver's heap happens to be collected.
_FILES_GO = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextmanager
def _shuffles_dropped(spark: SparkSession) -> Iterator[None]:
    before = spark.conf.get(_FILES_GO, None)
    spark.conf.set(_FILES_GO, "true")
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(_FILES_GO)
        else:
            spark.conf.set(_FILES_GO, before)


def written(df: DataFrame, label: str) -> DataFrame:
    """``df`` written once as a Parquet table in the shared folder and read back: lineage ends there, and its shuffle files go."""
    spark = df.sparkSession
    path = scratch_path(spark, label)
    with _shuffles_dropped(spark):
        df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop_since(spark: SparkSession, since: int, *kept: DataFrame, until: int | None = None) -> None:
    """Deletes the tables written from one :func:`mark` to another (or now), but for those that ``kept`` read."""
    stay = {f.rsplit("/", 2)[-2] for df in kept for f in df.inputFiles()}
    gone = {p for p in _PATHS[since:until] if p.rsplit("/", 1)[-1] not in stay}
    _PATHS[:] = [p for p in _PATHS if p not in gone]
    _delete(spark, gone)


def mark() -> int:
    """How many tables are written so far, for :func:`drop_since`."""
    return len(_PATHS)


def _delete(spark: SparkSession, paths: Iterable[str]) -> None:
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    for p in paths:
        path = jvm.org.apache.hadoop.fs.Path(p)
        path.getFileSystem(conf).delete(path, True)


def discard(spark: SparkSession) -> int:
    """Deletes all tables that this process wrote; for when no result that reads them is wanted any more. Returns how many."""
    gone = list(_PATHS)
    _PATHS.clear()
    _delete(spark, gone)
    return len(gone)
