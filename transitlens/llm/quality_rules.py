"""Quality rules at two levels: base rules on a document, and a verdict on its host.

Each rule comes from a document's own words; the first two are the base rules, which reject a document. A host (any column: a source, a
domain) collects how many of its documents fail each rule. Small hosts give noisy rates, so each rate is shrunk towards the mean of all
hosts: for each rule a beta prior is fitted to the hosts by moments (between-host variance less what binomial noise explains). A host
is rejected with all its documents if for any rule the lower end of its posterior rate (``Z`` standard deviations below the mean) is
above ``max_rate``: most of its documents surely fail that rule. The verdicts are joined back to the documents.

Work: one pass over the texts writes a narrow table; hosts are partial sums of it; the join carries no text.

Defined cases: a null or empty text has no words and fails the base rules; a null host is a host of its own; a repeated row counts
each time; an empty table gives an empty table; input columns of any other name are ignored (:func:`judge_documents`) or kept
(:func:`keep_good_documents`).
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import join_hosts, slices, text_or_empty, written

SYMBOLS = "#*$%&|<>"
SPACES = " \t\n\x0b\x0c\r"
WINDOW = 8
#: A document fails with fewer words than this, or with a larger share (percent) of its words in repeated windows.
MIN_WORDS, MAX_REPEAT = 20, 30
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def repeated_words(words: list[bytes], window: int = WINDOW) -> int:
    """Words inside a window of so many words (a power of two) that occurs at least twice; exact, by doubling of window ids."""
    if len(words) < window + 1:
        return 0
    seen: dict[bytes, int] = {}
    ids = np.fromiter((seen.setdefault(w, len(seen)) for w in words), np.int64, len(words))
    if len(seen) == len(words):
        return 0
    span = 1
    while span < window:
        pair = ids[:-span] * (int(ids.max()) + 1) + ids[span:]
        found, ids = np.unique(pair, return_inverse=True)
        if found.size == pair.size:
            return 0
        span *= 2
    twice = np.flatnonzero(np.bincount(ids)[ids] > 1)
    edge = np.zeros(len(words) + 1, np.int64)
    np.add.at(edge, twice, 1)
    np.add.at(edge, twice + window, -1)
    return int(np.count_nonzero(np.cumsum(edge)[:-1]))


def measure(text: str) -> tuple[int, int, int, int, int]:
    """The five measures of a text, in the order of ``MEASURES``."""
    words = text.encode("utf-8").split()
    chars = len(text) - sum(map(text.count, SPACES))
    symbols = sum(map(text.count, SYMBOLS))
    lines = text.split("\n")
    again = 0
    if len(set(lines)) < len(lines):
        full = [x for x in lines if x.strip(SPACES)]
        again = len(full) - len(set(full))
    return len(words), chars, symbols, again, repeated_words(words)


def with_measures(docs: DataFrame) -> DataFrame:
    """``docs`` with the five measures of ``text`` in place of ``text``."""
    rest = docs.drop(*MEASURES)
    rows = rest.select(*(text_or_empty().alias("text") if c == "text" else F.col(f"`{c}`") for c in rest.columns))
    where = rows.columns.index("text")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            others = [n for n in range(b.num_columns) if n != where]
            for lo, hi, texts in slices(b.column(where)):
                got = np.array([measure(t) for t in texts], np.int64)
                part = b.slice(lo, hi - lo)
                yield pa.RecordBatch.from_arrays([*(part.column(n) for n in others), *map(pa.array, np.ascontiguousarray(got.T))], names=[*(b.schema.names[n] for n in others), *MEASURES])

    fields = [f for f in rows.schema if f.name != "text"] + [T.StructField(m, T.LongType()) for m in MEASURES]
    return rows.mapInArrow(run, T.StructType(fields))


#: Rules on the measures; those of the first line reject a document by themselves.
RULES = {
    "few_words": f"n_words < {MIN_WORDS}", "repeats": f"100 * n_repeat_words > {MAX_REPEAT} * n_words",
    "symbols": "10 * n_symbols > word_chars", "lines": "20 * n_dup_lines > n_words",
}
#: Standard deviations below the posterior mean.
Z = 1.645


def base_failed() -> Column:
    return F.expr(f"({RULES['few_words']}) OR ({RULES['repeats']})")


def with_failures(measured: DataFrame) -> DataFrame:
    """``measured`` with ``base_failed`` and a column ``fails_...`` of 0 or 1 for each rule."""
    return measured.withColumns({"base_failed": base_failed()} | {f"fails_{r}": F.expr(f"CAST({test} AS BIGINT)") for r, test in RULES.items()})


def host_verdicts(judged: DataFrame, max_rate: float = 0.5) -> DataFrame:
    """``judged(host, fails_...)``, a written table, to ``(host, n_docs, n_..., low_..., host_rejected)``, a row per host: failures
    of each rule and the lower end of its rate."""
    counts = [F.sum(f"fails_{r}").alias(f"n_{r}") for r in RULES]
    hosts = written(judged.groupBy("host").agg(F.count("*").alias("n_docs"), *counts), "quality-host-counts")
    sums = [F.sum("n_docs").alias("n"), F.count("*").alias("h")]
    for r in RULES:
        sums += [F.sum(f"n_{r}").alias(f"f_{r}"), F.sum(F.col(f"n_{r}") * F.col(f"n_{r}") / F.col("n_docs")).alias(f"q_{r}")]
    total = hosts.agg(*sums).first()
    rejected = F.lit(False)
    for r in RULES:
        mean, weight = beta_prior(total["n"] or 0, total[f"f_{r}"] or 0, total["h"], total[f"q_{r}"] or 0.0)
        rate = (F.col(f"n_{r}") + F.lit(mean * weight)) / (F.col("n_docs") + F.lit(weight))
        hosts = hosts.withColumn(f"low_{r}", rate - Z * F.sqrt(rate * (1 - rate) / (F.col("n_docs") + F.lit(weight) + 1)))
        rejected = rejected | (F.col(f"low_{r}") > max_rate)
    return hosts.withColumn("host_rejected", rejected)


def beta_prior(n: int, failed: int, hosts: int, squares: float) -> tuple[float, float]:
    """Mean and weight (in documents) of the prior, from all hosts' sums; ``squares`` is the sum of n_failed**2 / n_docs.

    The weight lies between one document and a million; hosts that differ by no more than noise count as all alike.
    """
    if not n:
        return 0.0, 1.0
    mean = failed / n
    between = squares / n - mean * mean - mean * (1 - mean) * (hosts - 1) / n
    if between <= 0:
        return mean, 1e6
    return mean, min(1e6, max(1.0, mean * (1 - mean) / between - 1))


def judge_documents(docs: DataFrame, host: str = "source", max_rate: float = 0.5) -> DataFrame:
    """``(doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, host_rejected)`` of each document."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(host).cast("string").alias("host"), "text")
    judged = written(with_failures(with_measures(rows)), "quality-measures")
    out = join_hosts(judged, host_verdicts(judged, max_rate).select("host", "host_rejected"), "host")
    return out.select("doc_id", *MEASURES, "base_failed", (~F.col("base_failed") & ~F.col("host_rejected")).alias("kept"), "host_rejected")


def keep_good_documents(docs: DataFrame, host: str = "source", max_rate: float = 0.5) -> DataFrame:
    """The rows of ``docs``, all columns, that neither fail the base rules nor come from a rejected host."""
    marked = docs.select(F.struct("*").alias("row"), F.col(host).cast("string").alias("host"), text_or_empty().alias("text"))
    failures = [f"fails_{r}" for r in RULES]
    judged = written(with_failures(with_measures(marked)).select("row", "host", "base_failed", *failures), "quality-rows")
    hosts = host_verdicts(judged, max_rate).filter("host_rejected").select("host")
    return join_hosts(judged.filter(~F.col("base_failed")), hosts, "host", "left_anti").select("row.*")
