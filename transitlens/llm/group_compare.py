"""Pairs of near sketches inside groups, found in tiles of bounded size.

A group is the members that share a key. Groups of at most ``TILE`` members are one tile. Larger ones are dealt to tiles by a hash of
the member: a component with more members than that gets tiles of its own, the other members share some. Every tile meets every other
one of its group, but for those of one component among themselves; so a component of any size that meets few others costs a row a
member and tile of those others, never the square of its size. A pair of tiles is compared in one task, which holds those two only.

Inside a task members are compared as arrays; pairs of one component, of sizes that cannot link, or whose sketches are too far apart
never leave it.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Members of a tile, and words of sketches that a step of the comparison holds.
TILE, STEP = 256, 1 << 21


def _tiled(rows: DataFrame) -> DataFrame:
    """``rows(key, node, component, members, ...)`` with ``tile`` and the pair of tiles ``a``, ``b`` that meet; a row for each pair."""
    none = F.lit(0).cast("long")
    small = rows.filter(F.col("members") <= TILE).select("*", *(none.alias(c) for c in ("tile", "a", "b")))
    large = rows.filter(F.col("members") > TILE)
    sizes = large.groupBy("key", "component").agg(F.count("*").alias("n"))
    own = F.when(F.col("n") > TILE, F.ceil(F.col("n") / TILE)).otherwise(0).cast("long")
    sizes = sizes.withColumn("own", own)
    shared = F.ceil(F.sum(F.when(F.col("n") <= TILE, F.col("n")).otherwise(0)) / TILE).cast("long")
    keys = sizes.groupBy("key").agg(shared.alias("shared"), F.sum("own").alias("all_own"))
    before = Window.partitionBy("key").orderBy("component").rowsBetween(Window.unboundedPreceding, -1)
    big = sizes.filter("own > 0").select("key", "component", "own", F.coalesce(F.sum("own").over(before), F.lit(0)).alias("base"))
    large = large.join(keys, "key").join(big, ["key", "component"], "left")
    at = F.pmod(F.xxhash64("node"), F.coalesce("own", F.greatest(F.col("shared"), F.lit(1))))
    base = F.col("shared") + F.col("base")
    others = F.filter(F.sequence(none, F.col("shared") + F.col("all_own") - 1), lambda o: F.col("base").isNull() | (o < base) | (o >= base + F.col("own")))
    large = large.withColumn("tile", F.coalesce(base, none) + at).withColumn("o", F.explode(others))
    large = large.withColumns({"a": F.least("tile", "o"), "b": F.greatest("tile", "o")})
    return small.unionByName(large.select(small.columns))


def _apart(words: np.ndarray, start: np.ndarray, length: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Bits in which the sketches of rows ``i`` and ``j`` differ, the longer one folded to the length of the shorter."""
    least = np.minimum(length[i], length[j])
    out = np.zeros(i.size, np.int64)
    for w in np.unique(least):
        at = np.flatnonzero(least == w)
        need = np.unique(np.concatenate([i[at], j[at]]))
        folded = np.empty((need.size, w), np.uint64)
        for n in np.unique(length[need]):
            some = np.flatnonzero(length[need] == n)
            folded[some] = np.bitwise_xor.reduce(words[start[need[some], None] + np.arange(n)].reshape(some.size, n // w, w), axis=1)
        for lo in range(0, at.size, step := max(1, STEP // int(w))):
            part = at[lo : lo + step]
            x, y = (folded[np.searchsorted(need, side[part])] for side in (i, j))
            out[part] = np.bitwise_count(x ^ y).sum(axis=1, dtype=np.int64)
    return out


def near_pairs(group: np.ndarray, tile: np.ndarray, within: np.ndarray, component: np.ndarray, size: np.ndarray, sketch: pa.ListArray, offer: np.ndarray, percent: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows ``i < j`` of one group and different components whose sizes and sketches allow a link.

    Rows of a group lie together; where not ``within``, only rows of different tiles are compared. Of a group that is an ``offer``,
    each component gives its nearest pair only.
    """
    n = group.size
    end = np.searchsorted(group, group, side="right")
    words = sketch.flatten().to_numpy(zero_copy_only=False).view(np.uint64)
    stops = sketch.offsets.to_numpy().astype(np.int64)
    start, length = stops[:-1] - stops[0], np.diff(stops)
    found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    held: list[tuple[np.ndarray, np.ndarray]] = []

    def settle() -> None:
        if held:
            i, j = (np.concatenate(x) for x in zip(*held, strict=True))
            held.clear()
            d = _apart(words, start, length, i, j)
            ok = d <= (size[i] + size[j]) * (100 - percent) // (100 + percent)
            found.append((i[ok], j[ok], d[ok]))

    i, waiting = np.arange(n), 0
    for step in range(1, n):
        i = i[i + step < end[i]]
        if not i.size:
            break
        j = i + step
        go = (component[i] != component[j]) & (100 * size[i] >= percent * size[j]) & (100 * size[j] >= percent * size[i]) & (within[i] | (tile[i] != tile[j]))
        held.append((i[go], j[go]))
        waiting += int(go.sum())
        if waiting > 200_000:
            settle()
            waiting = 0
    settle()
    if not found:
        return i[:0], i[:0]
    i, j, d = (np.concatenate(x) for x in zip(*found, strict=True))
    keep = ~offer[i]
    for side in (i, j):
        order = np.lexsort((j, i, d, component[side], group[side]))
        order = order[offer[i[order]]]
        g, c = group[side[order]], component[side[order]]
        keep[order[np.append(True, (g[1:] != g[:-1]) | (c[1:] != c[:-1]))[: order.size]]] = True
    return i[keep], j[keep]


def near_in_groups(rows: DataFrame, percent: int) -> DataFrame:
    """``(u, v)``, repeated across groups, of ``rows(key, node, component, members, size, sketch, offer)``: pairs of one group and
    different components that may link; ``members`` counts the rows of a key."""
    tiles = _tiled(rows).select("key", "a", "b", "tile", "node", "component", F.col("size").cast("long").alias("size"), "offer", "sketch")
    tiles = tiles.repartition("key", "a", "b").sortWithinPartitions("key", "a", "b", "node")

    def compare(t: pa.Table) -> pa.RecordBatch:
        column = {c: t.column(c).to_numpy() for c in ("key", "a", "b", "tile", "node", "component", "size", "offer")}
        new = np.append(True, np.logical_or.reduce([column[c][1:] != column[c][:-1] for c in ("key", "a", "b")]))
        i, j = near_pairs(np.cumsum(new), column["tile"], column["a"] == column["b"], column["component"], column["size"], t.column("sketch").combine_chunks(), column["offer"].astype(bool), percent)
        x, y = column["node"][i], column["node"][j]
        return pa.RecordBatch.from_arrays([pa.array(np.minimum(x, y)), pa.array(np.maximum(x, y))], names=["u", "v"])

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rest: pa.Table | None = None  # of a pair of tiles whose end was not seen yet
        for b in batches:
            if not b.num_rows:
                continue
            t = pa.Table.from_batches([b])
            rest = t if rest is None else pa.concat_tables([rest, t])
            last = np.logical_and.reduce([rest.column(c).to_numpy() == rest.column(c)[-1].as_py() for c in ("key", "a", "b")])
            whole = int(last.argmax())
            if whole:
                yield compare(rest.slice(0, whole))
                rest = rest.slice(whole)
        if rest is not None:
            yield compare(rest)

    return tiles.mapInArrow(run, "u long, v long")
