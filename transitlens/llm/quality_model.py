"""Quality classifier: a sparse ensemble of rules over text statistics, compiled into one column expression.

Statistics are DataFrame functions of a text. Small trees, boosted on labelled rows, propose rules: each path from a root is a
conjunction of comparisons. A lasso logistic regression over the rules keeps few and weighs them; its penalty is the one that does
best on a fifth of the training rows held back. The kept rules become a Spark column, so scoring is a projection.

Fitting takes at most ``most_rows`` labelled ids (documented bound, picked by a hash of the id) to the driver; statistics and scores
cover every row.

Defined cases: a null text counts as empty, whose statistics are all 0, and gets a score like any other; labels that are null, other than
0 and 1, or for an id without a document are ignored; an id labelled both ways is ignored; an id that
repeats trains once, with the least of its rows; without labels of both classes the score is their smoothed share everywhere; an empty table gives an empty table; other
columns are never read.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import text_or_empty, written

#: Labelled rows that a fit takes at most.
MOST_ROWS = 10_000
SPACE = r"[\x20\x09-\x0D]+"


def with_text_statistics(rows: DataFrame) -> DataFrame:
    """``rows(text, ...)`` with a column for each of ``NAMES`` in place of ``text``; shares are of its characters, words or lines."""
    text, n = F.col("text"), F.length("text")

    def share(part: Column, whole: Column) -> Column:
        return F.when(whole > 0, part / whole).otherwise(F.lit(0.0))

    def chars(some: str) -> Column:
        return share(n - F.length(F.translate(text, some, "")), n)

    # Words and lines are columns of their own, so that they are cut once.
    rows = rows.withColumns({"_words": F.filter(F.split(text, SPACE), lambda w: w != ""), "_lines": F.filter(F.split(text, "\n"), lambda x: F.trim(x) != "")})
    n_words, n_lines = F.size("_words"), F.size("_lines")
    found = {
        "n_words": n_words.cast("double"),
        "word_length": share(F.length(F.translate(text, " \n\t\r\x0b\x0c", "")), n_words),
        "symbols": chars("#*$%&|<>"),
        "upper": chars("ABCDEFGHIJKLMNOPQRSTUVWXYZ"),
        "digits": chars("0123456789"),
        "marks": chars("!?"),
        "stops": chars(".,;:"),
        "pipes": chars("|"),
        "distinct_words": share(F.size(F.array_distinct("_words")), n_words),
        "distinct_lines": share(F.size(F.array_distinct("_lines")), n_lines),
        "line_words": share(n_words, n_lines),
    }
    kept = [c for c in rows.columns if c not in ("text", "_words", "_lines")]
    return rows.select(*kept, *(found[k].cast("double").alias(k) for k in NAMES))


NAMES = ("n_words", "word_length", "symbols", "upper", "digits", "marks", "stops", "pipes", "distinct_words", "distinct_lines", "line_words")


@dataclass(frozen=True)
class Term:
    """A comparison: statistic above the threshold, or not above."""

    name: str
    above: bool
    threshold: float


Rule = tuple[Term, ...]


@dataclass(frozen=True)
class RuleModel:
    """Kept rules with weights, and the intercept."""

    rules: tuple[tuple[Rule, float], ...]
    intercept: float

    def score(self) -> Column:
        """The probability of label 1 as a column over the statistics' columns."""
        total = F.lit(self.intercept)
        for rule, weight in self.rules:
            fits = F.lit(True)
            for t in rule:
                fits = fits & ((F.col(t.name) > t.threshold) if t.above else (F.col(t.name) <= t.threshold))
            total = total + F.when(fits, F.lit(weight)).otherwise(F.lit(0.0))
        return 1.0 / (1.0 + F.exp(-total))

    def score_rows(self, x: np.ndarray) -> np.ndarray:
        total = np.full(len(x), self.intercept)
        for rule, weight in self.rules:
            total += weight * _holds(rule, x)
        return 1 / (1 + np.exp(-total))


def _holds(rule: Rule, x: np.ndarray) -> np.ndarray:
    fits = np.ones(len(x), bool)
    for t in rule:
        v = x[:, NAMES.index(t.name)]
        fits &= v > t.threshold if t.above else v <= t.threshold
    return fits


def _grow(x: np.ndarray, grad: np.ndarray, hess: np.ndarray, rows: np.ndarray, fit: np.ndarray, cuts: list[np.ndarray], columns: np.ndarray, depth: int, path: Rule, out: list[Rule]) -> np.ndarray:
    """Grows a tree of second-order gain on those of ``rows`` that ``fit`` marks; adds each node's path to ``out`` and returns the
    step of each of ``rows``."""
    own = rows[fit[rows]]
    g, h = grad[own].sum(), hess[own].sum()
    step = np.full(rows.size, -g / (h + 1.0))
    if depth == 0 or own.size < 40:
        return step
    best = (1e-6, -1, 0.0)
    for c in columns:
        if not cuts[c].size:
            continue
        where = np.searchsorted(cuts[c], x[own, c], side="left")
        gl, hl, nl = (np.cumsum(np.bincount(where, v, cuts[c].size + 1))[:-1] for v in (grad[own], hess[own], np.ones(own.size)))
        gain = gl**2 / (hl + 1) + (g - gl) ** 2 / (h - hl + 1) - g**2 / (h + 1)
        gain[(nl < 20) | (own.size - nl < 20)] = -1
        i = int(gain.argmax())
        if gain[i] > best[0]:
            best = (gain[i], c, float(cuts[c][i]))
    _, c, cut = best
    if c < 0:
        return step
    right = x[rows, c] > cut
    for above in (False, True):
        longer = (*path, Term(NAMES[c], above, cut))
        out.append(longer)
        step[right == above] = _grow(x, grad, hess, rows[right == above], fit, cuts, columns, depth - 1, longer, out)
    return step


def propose_rules(x: np.ndarray, y: np.ndarray, trees: int = 40, depth: int = 3, seed: int = 7) -> list[Rule]:
    """Paths of boosted trees, each on half of the rows and most of the statistics."""
    rng = np.random.default_rng(seed)
    cuts = [np.unique(np.quantile(x[:, c], np.linspace(0.01, 0.99, 63))) for c in range(x.shape[1])]
    total = np.full(len(x), np.log(max(y.mean(), 1e-3) / max(1 - y.mean(), 1e-3)))
    rate = 0.3
    out: list[Rule] = []
    for _ in range(trees):
        p = 1 / (1 + np.exp(-total))
        fit = rng.random(len(x)) < 0.5
        columns = np.sort(rng.choice(x.shape[1], max(1, x.shape[1] * 3 // 4), replace=False))
        total += rate * _grow(x, p - y, p * (1 - p), np.arange(len(x)), fit, cuts, columns, depth, (), out)
    # Rules that cover the same training rows are one.
    first: dict[bytes, Rule] = {}
    for rule in sorted(set(out), key=lambda r: (len(r), r[-1].name, r[-1].threshold)):
        fits = _holds(rule, x)
        if 0.002 < fits.mean() < 0.998:
            first.setdefault(np.packbits(fits).tobytes(), rule)
    return list(first.values())


def lasso_logistic(a: np.ndarray, y: np.ndarray, penalty: float, steps: int = 300) -> tuple[np.ndarray, float]:
    """Weights and intercept by accelerated proximal gradient; columns of ``a`` are 0 or 1, and equal rows are taken together."""
    n, m = a.shape
    packed, group = np.unique(np.packbits(a.astype(bool), axis=1), axis=0, return_inverse=True)
    a = np.unpackbits(packed, axis=1, count=m).astype(float)
    rows, ones = np.bincount(group.ravel()) / n, np.bincount(group.ravel(), y) / n
    w, b = np.zeros(m), float(np.log(max(y.mean(), 1e-3) / max(1 - y.mean(), 1e-3)))
    v, c, t = w.copy(), b, 1.0
    # The largest curvature, by a few power steps over rules and intercept.
    u = np.ones(m + 1)
    for _ in range(20):
        z = rows * (a @ u[:m] + u[m])
        u = np.append(a.T @ z, z.sum())
        top = np.linalg.norm(u)
        u /= max(top, 1e-12)
    lip = 0.3 * top + 1e-9
    for _ in range(steps):
        gap = rows / (1 + np.exp(-(a @ v + c))) - ones
        w2 = v - a.T @ gap / lip
        w2 = np.sign(w2) * np.maximum(np.abs(w2) - penalty / lip, 0)
        b2 = c - gap.sum() / lip
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        v, c = w2 + (t - 1) / t2 * (w2 - w), b2 + (t - 1) / t2 * (b2 - b)
        w, b, t = w2, b2, t2
    return w, float(b)


def fit_rules(x: np.ndarray, y: np.ndarray) -> RuleModel:
    """The model of training rows ``x`` (a column for each of ``NAMES``) and labels ``y``."""
    if len(y) == 0 or y.min() == y.max():
        share = (y.sum() + 1) / (len(y) + 2)
        return RuleModel((), float(np.log(share / (1 - share))))
    rules = propose_rules(x, y)
    a = np.stack([_holds(r, x) for r in rules], axis=1).astype(float) if rules else np.zeros((len(y), 0))
    held = np.arange(len(y)) % 5 == 4
    best = (np.inf, 0.01)
    for penalty in (0.03, 0.01, 0.003, 0.001, 0.0003):
        w, b = lasso_logistic(a[~held], y[~held], penalty, 150)
        p = np.clip(1 / (1 + np.exp(-(a[held] @ w + b))), 1e-6, 1 - 1e-6)
        loss = -(y[held] * np.log(p) + (1 - y[held]) * np.log(1 - p)).mean()
        if loss < best[0] - 1e-4:
            best = (loss, penalty)
    w, b = lasso_logistic(a, y, best[1], 400)
    return RuleModel(tuple((r, float(v)) for r, v in zip(rules, w, strict=True) if v != 0), b)


def held_out() -> Column:
    return F.crc32(F.col("doc_id").cast("string")) % 5 == 0


def with_statistics(docs: DataFrame) -> DataFrame:
    """``(doc_id, statistics...)`` of each row; written."""
    return written(with_text_statistics(docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text"))), "quality-statistics")


def training_rows(stats: DataFrame, labels: DataFrame, most_rows: int = MOST_ROWS) -> tuple[np.ndarray, np.ndarray]:
    """Statistics and labels of labelled ids that are not held out. Where there are more than ``most_rows``, those with a hash below a
    threshold, some less than that number: so what the driver gets is bounded, and no task sends more than its share."""
    marks = labels.select(F.col("doc_id").cast("long").alias("_id"), F.col("quality").cast("int").alias("y")).filter("_id IS NOT NULL AND y IN (0, 1)")
    marks = marks.groupBy("_id").agg(F.min("y").alias("y"), F.max("y").alias("_top")).filter("y = _top").drop("_top")
    marks = marks.filter(F.crc32(F.col("_id").cast("string")) % 5 != 0)
    n, buckets = marks.count(), 1 << 24
    marks = marks.filter(F.pmod(F.xxhash64("_id"), F.lit(buckets)) < (buckets if n <= most_rows else int(buckets * max(1.0, most_rows - 5 * most_rows**0.5) / n)))
    rows = stats.join(marks, stats["doc_id"] == marks["_id"]).groupBy("doc_id", "y").agg(F.min(F.struct(*NAMES)).alias("s"))
    got = rows.select(F.xxhash64("doc_id").alias("h"), "doc_id", "y", "s.*").toPandas().sort_values(["h", "doc_id"]).head(most_rows)
    return got[list(NAMES)].to_numpy(float), got["y"].to_numpy(float)


def quality_scores(docs: DataFrame, labels: DataFrame, cut: float = 0.3, most_rows: int = MOST_ROWS) -> DataFrame:
    """``(doc_id, held_out, score, predicted)`` of each document; ``labels(doc_id, quality)`` serve for fitting only."""
    stats = with_statistics(docs)
    model = fit_rules(*training_rows(stats, labels, most_rows))
    scored = stats.select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), model.score().alias("score"))
    return scored.withColumn("predicted", (F.col("score") >= cut).cast("int"))
