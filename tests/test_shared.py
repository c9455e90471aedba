"""Written tables: what stays on disk beside them."""

import os
import time

from transitlens.plans.shared import _FILES_GO, drop_since, mark, written


def _shuffle_files(spark):
    manager = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()
    return {f for d in manager.localDirsString() for _, _, files in os.walk(d) for f in files if f.startswith("shuffle_")}


def test_a_written_table_leaves_no_shuffle_files(spark):
    before, was = _shuffle_files(spark), spark.conf.get(_FILES_GO, None)
    rows = spark.range(20_000).selectExpr("id % 7000 AS a").distinct()
    table = written(rows, "test-shuffles")
    until = time.time() + 10  # files are deleted in the background
    while (left := _shuffle_files(spark) - before) and time.time() < until:
        time.sleep(0.2)
    assert not left
    assert table.count() == rows.count() == 7000
    assert spark.conf.get(_FILES_GO, None) == was


def test_tables_that_nothing_reads_any_more_are_deleted(spark):
    first = written(spark.range(3), "test-first")
    start = mark()
    gone, stays = written(spark.range(4), "test-gone"), written(spark.range(5), "test-stays")
    place = gone.inputFiles()[0].rsplit("/", 1)[0].removeprefix("file://")
    drop_since(spark, start, stays.filter("id > 1"))
    assert not os.path.exists(place)
    assert first.count() == 3 and stays.count() == 5
