"""Exact k best inner products by block-at-a-time pruning.

Components become integers, floor(scale * x). Candidates are dealt to tiles by a hash of their row; queries, likewise, to tiles of
their own; a candidate tile meets every query tile once, in a task that holds one of each. Inside a tile the candidates are put in an
order that brings like vectors together, and cut to ranges (blocks). The terms of the bounds are the tile's main directions, an
orthogonal basis of which the first few hold most of the squared lengths: a block keeps, per term, its largest and smallest value, and
the greatest length of what the other directions hold, so the sum over the terms of the larger product, plus the product of the lengths
left, bounds every score in it. A query visits blocks in order of their bounds and scores each through the block's rows, until the next
bound falls below its k-th score.

Two rounds carry that score across tiles: in the first a query meets one tile only, and its k-th score there is where it starts in all
others. Then one merge per query.

Scores are exact: in 64-bit floats where no sum can leave the whole numbers that these hold, else in Python's integers; rows with
large components have tiles of their own. A score beyond 64 bits is given as the nearest 64-bit integer and ranked by its double.

Defined cases: vectors that are null or empty, or that hold a null or non-finite component, take no part, nor do rows without an id; a
query meets candidates of its own length; rows that repeat an id each take part, a query meets all rows but its own; ties go to the
smaller id; fewer candidates than k give fewer rows; an empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import written

#: Rows of a candidate tile, of a query tile, and of a block; terms of a bound.
TILE, QUERIES, BLOCK, TERMS = 8192, 16_384, 64, 16
#: Components up to here are multiplied as floats: products of up to 2**13 of them stay whole.
NARROW = float(1 << 20)
_LOW, _HIGH = np.iinfo(np.int64).min, np.iinfo(np.int64).max


def quantised(vectors: DataFrame, scale: int = 256, vec_id: str = "vec_id", embedding: str = "embedding") -> DataFrame:
    """``(vec_id, q, wide)`` of the rows that take part; ``q`` holds whole numbers as doubles, ``wide`` tells rows with large ones."""
    x = F.col(embedding).cast("array<double>")
    good = F.forall(x, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < F.lit(float("inf"))))
    rows = vectors.filter(F.col(vec_id).isNotNull() & (F.size(x) > 0) & good)
    # From 2**52 on a double is a whole number already.
    q = F.transform(x, lambda v: F.when(F.abs(scale * v) < float(1 << 52), F.floor(scale * v).cast("double")).otherwise(scale * v))
    return rows.select(F.col(vec_id).cast("long").alias("vec_id"), q.alias("q")).withColumn("wide", F.exists("q", lambda v: F.abs(v) > NARROW))


def _order(y: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """An order that brings like rows together: halves along the widest of the first directions, down to blocks."""
    if rows.size <= BLOCK:
        return rows
    part = y[rows]
    d = int(np.argmax(part.max(axis=0) - part.min(axis=0)))
    half = max(BLOCK, rows.size // 2 // BLOCK * BLOCK)
    by = np.argpartition(part[:, d], half - 1) if half < rows.size else np.arange(rows.size)
    return np.concatenate([_order(y, rows[by[:half]]), _order(y, rows[by[half:]])]) if half < rows.size else rows


def _rest(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return np.sqrt(np.maximum((x * x).sum(axis=1) - (y * y).sum(axis=1), 0) + 1e-9 * (x * x).sum(axis=1))


def search_tile(ids: np.ndarray, own: np.ndarray, rows: np.ndarray, query_own: np.ndarray, queries: np.ndarray, k: int, floor: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """Query numbers, candidate rows (their places) and scores of each query's k best in a tile, and the number of blocks scored.

    ``own`` and ``query_own`` name rows, so that a query misses itself; ``floor`` is a score that each query's results must reach.
    """
    n, m = len(queries), len(rows)
    if not (n and m):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, object), 0
    exact = max(np.abs(rows).max(), 1) * max(np.abs(queries).max(), 1) * rows.shape[1] < float(1 << 53)
    _, basis = np.linalg.eigh((rows / max(1.0, np.abs(rows).max())).T @ (rows / max(1.0, np.abs(rows).max())))
    basis = basis[:, ::-1][:, :TERMS]
    y, z = rows @ basis, queries @ basis
    order = _order(y[:, : min(8, y.shape[1])], np.arange(m))
    starts = np.arange(0, m, BLOCK)
    high, low, rest = np.maximum.reduceat(y[order], starts), np.minimum.reduceat(y[order], starts), np.maximum.reduceat(_rest(rows, y)[order], starts)
    up = np.maximum(z, 0) @ high.T + np.minimum(z, 0) @ low.T + _rest(queries, z)[:, None] * rest[None, :]
    up += 1e-6 * np.abs(queries).sum(axis=1)[:, None] * max(np.abs(rows).max(), 1)  # more than rounding can lose
    visit = np.argsort(-up, axis=1, kind="stable")
    if not exact:
        rows, queries = (np.frompyfunc(int, 1, 1)(x) for x in (rows, queries))
    none = -np.inf
    best = np.full((n, k), none, float if exact else object)
    best_at = np.full((n, k), -1)
    bar = np.full(n, -np.inf) if floor is None else floor.astype(float)
    scored, live = 0, np.arange(n)
    for turn in range(visit.shape[1]):
        at = visit[live, turn]
        # A bound equal to the k-th score may still hold a smaller id.
        go = up[live, at] >= np.maximum(bar[live], np.nextafter(best[live, -1].astype(float), -np.inf))
        live, at = live[go], at[go]
        if not live.size:
            break
        scored += live.size
        for b in np.unique(at):
            who, span = live[at == b], order[b * BLOCK : (b + 1) * BLOCK]
            score = queries[who] @ rows[span].T
            score[own[span][None, :] == query_own[who][:, None]] = none
            all_s = np.concatenate([best[who], score], axis=1)
            all_at = np.concatenate([best_at[who], np.broadcast_to(span, score.shape)], axis=1)
            name = np.where(all_at < 0, _HIGH, ids[all_at])
            if exact:
                pick = np.lexsort((name, -all_s), axis=1)[:, :k]
            else:
                pick = np.array([sorted(range(len(s)), key=lambda c: (-s[c], i[c]))[:k] for s, i in zip(all_s, name, strict=True)])
            best[who], best_at[who] = np.take_along_axis(all_s, pick, 1), np.take_along_axis(all_at, pick, 1)
    q, r = np.nonzero(best != none)
    return q, best_at[q, r], best[q, r], scored


def _saturated(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Scores as 64-bit integers, those beyond as the nearest, and as doubles."""
    return np.array([min(max(int(v), _LOW), _HIGH) for v in x], np.int64), x.astype(float)


def _dealt(rows: DataFrame, name: str, size: int, salt: int) -> tuple[DataFrame, int]:
    """``rows`` with the number of each one's tile as ``name``, and how many tiles there are; those of wide rows come last."""
    n = {r["wide"]: r["count"] for r in rows.groupBy("wide").count().collect()}
    plain, wide = (-(-n.get(w, 0) // size) for w in (False, True))
    at = F.xxhash64(F.lit(salt), "own")
    tile = F.when(F.col("wide"), plain + F.pmod(at, F.lit(max(1, wide)))).otherwise(F.pmod(at, F.lit(max(1, plain))))
    return rows.withColumn(name, tile.cast("int")).drop("wide"), plain + wide


def top_k(vectors: DataFrame, is_query: Column, k: int = 5, scale: int = 256, vec_id: str = "vec_id", embedding: str = "embedding") -> DataFrame:
    """``(query_id, rank, vec_id, score)``: the k best of all other rows for each row that ``is_query`` (of ``vec_id``) picks."""
    rows = quantised(vectors, scale, vec_id, embedding).withColumns({"dim": F.size("q"), "own": F.monotonically_increasing_id()})
    rows = written(rows, "topk-vectors")  # so the names of rows are settled
    candidates, n_c = _dealt(rows, "c", TILE, 1)
    queries, n_q = _dealt(rows.filter(is_query), "t", QUERIES, 2)

    def matrix(t: pa.Table) -> np.ndarray:
        return np.asarray(t.column("q").combine_chunks().flatten(), np.float64).reshape(t.num_rows, -1)

    def run(c: pa.Table, q: pa.Table) -> pa.Table:
        who, at, score = np.zeros(0, int), np.zeros(0, int), np.zeros(0)
        ids, own = (c.column(x).to_numpy() for x in ("vec_id", "own"))
        names, mine = (q.column(x).to_numpy() for x in ("vec_id", "own"))
        if c.num_rows and q.num_rows:
            floor = q.column("floor").to_numpy().astype(float)
            who, at, score, _ = search_tile(ids, own, matrix(c), mine, matrix(q), k, np.where(np.isnan(floor), -np.inf, floor))
        whole, value = _saturated(score)
        return pa.table({"query_own": pa.array(mine[who], pa.int64()), "query_id": pa.array(names[who], pa.int64()), "vec_id": pa.array(ids[at], pa.int64()), "score": pa.array(whole, pa.int64()), "value": pa.array(value, pa.float64())})

    def met(pairs: Column, asked: DataFrame) -> DataFrame:
        """Scores of those pairs of tiles (``pairs``, of ``c`` and ``t``) that meet: rows are repeated for each tile opposite."""
        left = candidates.withColumn("t", F.explode(F.sequence(F.lit(0), F.lit(max(0, n_q - 1))))).filter(pairs)
        right = asked.withColumn("c", F.explode(F.sequence(F.lit(0), F.lit(max(0, n_c - 1))))).filter(pairs)
        right = right.select(*(F.col(x).alias(x) for x in right.columns))  # columns of its own, as both sides come from one table
        keys = ["c", "t", "dim"]
        return left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInArrow(run, "query_own long, query_id long, vec_id long, score long, value double")

    best = Window.partitionBy("query_own").orderBy(F.desc("score"), F.desc("value"), "vec_id")
    home = F.col("c") == F.pmod(F.col("t"), F.lit(max(1, n_c)))
    found = met(home, queries.withColumn("floor", F.lit(float("nan"))))
    if n_c > 1:
        found = written(found, "topk-first")
        # A value may be rounded: the bar is set below it.
        bar = F.col("value") - F.abs("value") * 1e-15
        kth = found.withColumn("nth", F.row_number().over(best)).filter(F.col("nth") == k).select(F.col("query_own").alias("own"), bar.alias("floor"))
        asked = queries.join(kth, "own", "left").withColumn("floor", F.coalesce("floor", F.lit(float("nan"))))
        found = found.unionByName(met(~home, asked))
    return found.withColumn("rank", F.row_number().over(best)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
