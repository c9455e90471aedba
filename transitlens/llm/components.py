"""Connected components of a link table, by hooking to smaller neighbours and pointer jumping; tables stay in the cluster."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop_written, written


def _jumped(parents: DataFrame) -> DataFrame:
    """``parents(node, parent)``, each parent smaller than its node, with every node pointing at its root; written."""
    now = written(parents, "cc-parents")
    while True:
        up = now.select(F.col("node").alias("parent"), F.col("parent").alias("next"))
        new = written(now.join(up, "parent", "left").select("node", F.coalesce("next", "parent").alias("parent"), F.col("next").isNotNull().alias("moved")), "cc-parents")
        drop_written(now)
        now = new
        if now.filter("moved").isEmpty():
            return now.select("node", "parent")


def connected_components(links: DataFrame) -> DataFrame:
    """``links(u, v)`` of integers to ``(node, component)``, the smallest node reachable; nodes without a link have no row.

    A round lets every node point at its smallest neighbour if that is smaller, jumps pointers to the roots and replaces nodes by
    roots in the links; the links left join different roots. Rounds are logarithmic in the size of a component. Null ends are
    ignored.
    """
    left = written(links.select("u", "v").filter("u <> v"), "cc-links")
    labels = None
    while not left.isEmpty():
        both = left.unionByName(left.select(F.col("v").alias("u"), F.col("u").alias("v")))
        roots = _jumped(both.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("parent")).filter("parent < node"))
        if labels is None:
            named = both.select(F.col("u").alias("node")).distinct().join(roots, "node", "left").select("node", F.coalesce("parent", "node").alias("component"))
        else:
            named = labels.join(roots.withColumnRenamed("node", "component"), "component", "left").select("node", F.coalesce("parent", "component").alias("component"))
        labels = written(named, "cc-labels")
        for end in ("u", "v"):
            left = left.join(roots.select(F.col("node").alias(end), F.col("parent").alias("_root")), end, "left").withColumn(end, F.coalesce("_root", end)).drop("_root")
        left = written(left.filter("u <> v").distinct(), "cc-links")
    return labels if labels is not None else left.select(F.col("u").alias("node"), F.col("v").alias("component"))
