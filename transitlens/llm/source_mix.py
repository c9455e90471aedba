"""Mixing sources to target weights by hash-threshold histograms; DataFrame functions only.

Each document has a hash; a source's budget is met by all documents with a hash below a threshold, and a larger budget has a larger
threshold, so mixes are nested. To find the threshold, sizes are summed by source and hash bucket, running sums find the bucket in
which the budget ends, and only that bucket's documents are summed again by finer buckets, until it holds one hash. Nothing is
sorted but the histograms, at most ``2**BITS`` rows a source; a level reads a thousandth of the last one's rows.

A source whose target is above its size gives each document as often as the target holds its size, and the rest by threshold.

Defined cases: a null text has size 0; a null source is a source of its own, last in order; a source of size 0 has target 0; rows
equal in id and text share a hash and are taken together; the document in which a budget ends is taken if that comes nearer; an
empty table gives an empty table. Other columns are ignored (:func:`mix_documents`) or kept (:func:`mixed_rows`).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, join_hosts, text_or_empty, written

#: Bits of the hash, and of them those that a level of the histogram takes.
HASH_BITS, BITS = 60, 10


def n_words(name: str = "text") -> Column:
    return F.regexp_count(text_or_empty(name), F.lit(WORD)).cast("long")


def mix_hash(seed: int = 0) -> Column:
    return F.xxhash64(F.lit(seed), "doc_id", "text").bitwiseAND((1 << HASH_BITS) - 1)


def sized(docs: DataFrame, seed: int = 0) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), n_words().alias("size"), mix_hash(seed).alias("hash"))


def source_targets(sources: DataFrame, weights: tuple[float, ...] = (1, 2, 3), most: float = 3, share: float = 1.0) -> DataFrame:
    """``sources(source, source_size)``, a row per source, with the ``target`` of each.

    Targets are in proportion to the weights (repeating in code point order) but at most ``most`` times the source's size; what is
    above is shared again by weight. So there is one level: sources whose cap by weight is below it are capped, the others stand at
    level times weight. Running sums over the sources in order of cap by weight give the level.
    """
    order = Window.orderBy(F.col("source").asc_nulls_last())
    cycle = F.array(*map(F.lit, map(float, weights)))
    ranked = sources.withColumn("weight", cycle[(F.row_number().over(order) - 1) % len(weights)]).withColumn("cap", F.col("source_size") * F.lit(float(most)))
    by_cap = Window.orderBy(F.col("cap") / F.col("weight"), F.col("source").asc_nulls_last())
    before, whole = by_cap.rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy(F.lit(1))
    left = F.sum("source_size").over(whole) * F.lit(float(share)) - F.coalesce(F.sum("cap").over(before), F.lit(0.0))
    over = F.sum("weight").over(whole) - F.coalesce(F.sum("weight").over(before), F.lit(0.0))
    ranked = ranked.withColumn("level", left / over)
    # The first source that its share does not fill sets the level for all from there.
    level = F.min(F.when(F.col("level") <= F.col("cap") / F.col("weight"), F.struct(F.col("cap") / F.col("weight"), "level"))).over(whole)["level"]
    return ranked.withColumn("target", F.when(level.isNull(), F.col("cap")).otherwise(F.least("cap", level * F.col("weight")))).select("source", "source_size", "target")


def thresholds(rows: DataFrame, budgets: DataFrame) -> DataFrame:
    """``budgets(source, budget, ...)`` with the hash ``threshold`` of each: documents below it come nearest to the budget."""
    spark = rows.sparkSession
    # An open source: the budget ends in the bucket of hashes whose upper bits are ``prefix``.
    open_ = budgets.select("source", F.lit(0).cast("long").alias("prefix"), F.col("budget").alias("left"))
    done, shift = [], HASH_BITS
    while shift > 0:
        inside = rows if shift == HASH_BITS else None
        cell = F.shiftright("hash", shift - BITS)
        if inside is None:
            inside = join_hosts(rows.withColumn("_at", F.struct("source", F.shiftright("hash", shift).alias("prefix"))), open_.select(F.struct("source", "prefix").alias("_at")), "_at", "left_semi").drop("_at")
        cells = inside.groupBy("source", cell.alias("cell")).agg(F.sum("size").alias("words"), F.min("hash").alias("low"), F.max("hash").alias("high"))
        w = Window.partitionBy("source").orderBy("cell")
        cells = join_hosts(cells, open_.select("source", "left"), "source").withColumn("upto", F.sum("words").over(w))
        cut = cells.filter(F.col("upto") >= F.col("left")).groupBy("source").agg(F.min(F.struct("cell", "upto", "words", "low", "high", "left")).alias("c")).select("source", "c.*")
        cut = written(cut.withColumn("rest", F.col("left") - (F.col("upto") - F.col("words"))), "mix-cut")
        one = F.col("low") == F.col("high")
        take = F.col("upto") - F.col("left") <= F.col("rest")
        done.append(cut.filter(one).select("source", (F.col("low") + take.cast("long")).alias("threshold")))
        open_ = cut.filter(~one).select("source", F.col("cell").alias("prefix"), F.col("rest").alias("left"))
        shift -= BITS
        if open_.isEmpty():
            break
    found = done[0]
    for d in done[1:]:
        found = found.unionByName(d)
    found = written(found, "mix-thresholds")
    return budgets.join(F.broadcast(found.withColumnRenamed("source", "_s")) if found.count() <= 100_000 else found.withColumnRenamed("source", "_s"), F.col("source").eqNullSafe(F.col("_s")), "left").drop("_s").withColumn("threshold", F.coalesce("threshold", F.lit(0)))


def mix_plan(rows: DataFrame, weights: tuple[float, ...] = (1, 2, 3), most: float = 3, share: float = 1.0) -> DataFrame:
    """A row per source of ``rows(source, size, hash)``: size, target, whole repeats and the threshold of one more; written."""
    sources = written(rows.groupBy("source").agg(F.sum("size").alias("source_size")), "mix-sources")
    targets = source_targets(sources, weights, most, share)
    repeats = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long")
    plan = written(targets.withColumn("repeats", repeats).withColumn("budget", F.col("target") - F.col("repeats") * F.col("source_size")), "mix-targets")
    need = plan.filter("budget > 0")
    found = thresholds(rows, need).select("source", "threshold")
    return written(join_hosts(plan, found, "source", "left").withColumn("threshold", F.coalesce("threshold", F.lit(0))), "mix-plan")


def copies() -> Column:
    return F.col("repeats") + (F.col("hash") < F.col("threshold")).cast("long")


def mix_documents(docs: DataFrame, weights: tuple[float, ...] = (1, 2, 3), most: float = 3, seed: int = 0) -> DataFrame:
    """``(doc_id, size, source_size, target, taken, copies)`` of each document."""
    rows = written(sized(docs, seed), "mix-sizes")
    plan = mix_plan(rows, weights, most)
    out = join_hosts(rows, plan.select("source", "source_size", "target", "repeats", "threshold"), "source").withColumn("copies", copies())
    return out.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"), "copies")


def mixed_rows(docs: DataFrame, weights: tuple[float, ...] = (1, 2, 3), most: float = 3, seed: int = 0) -> DataFrame:
    """The mix itself: each row of ``docs``, all its columns, as often as the mix takes it."""
    plan = mix_plan(written(sized(docs, seed), "mix-sizes"), weights, most).select("source", "repeats", "threshold")
    rows = docs.select(F.struct("*").alias("row"), F.col("source").cast("string").alias("source"), mix_hash(seed).alias("hash"))
    out = join_hosts(rows, plan, "source").withColumn("copies", copies()).filter("copies > 0")
    return out.withColumn("nth", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies")))).select("row.*")
