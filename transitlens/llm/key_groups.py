"""Groups of documents that carry an equal key, met through packed blocks instead of a row for each document and key.

A key has ``KEY_BYTES`` bytes; its leading bits name a bucket. A task sorts the keys of many documents at once and writes one block per
bucket: each key as its distance from the one before, each document as its distance from the smallest id, both in as few bytes as the
block needs. All blocks of a bucket meet in one task, which takes them some at a time: what it holds between them is one document for
each distinct key of the bucket, so a key that all documents carry costs no more than any other.

Different values whose keys are equal put documents in one group that need not be; whoever reads the groups compares their members.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

KEY_BYTES = 5
#: Keys of a bucket, about; buckets at least, as a power of two.
BUCKET, LEAST_BITS = 1 << 20, 8
#: Keys that a task packs at once, or takes from blocks at once.
STEP = 1 << 21
#: Ids of a bitmap, and bitmaps of 4 KB that are sent to each task; above, documents are picked by a join.
MAP_IDS, MOST_MAPS = 1 << 15, 1 << 14
#: Keys that are sent to each task at most.
MOST_KEYS = 4_000_000

_BLOCK = pa.schema([("bucket", pa.int32()), ("base", pa.int64()), ("new", pa.bool_()), ("key_width", pa.int32()), ("node_width", pa.int32()), ("keys", pa.binary()), ("nodes", pa.binary())])
_BLOCK_SQL = "bucket int, base long, new boolean, key_width int, node_width int, keys binary, nodes binary"
_MEETING_SQL = "key long, node long, center long, new boolean"


def low_bytes(x: np.ndarray, width: int) -> np.ndarray:
    """The low ``width`` bytes of each number, end to end."""
    return np.ascontiguousarray(x.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width]).ravel()


def from_bytes(raw: np.ndarray, width: int) -> np.ndarray:
    out = np.zeros((raw.size // width if width else 0, 8), np.uint8)
    out[:, :width] = raw.reshape(-1, width) if width else 0
    return out.view("<u8").ravel().astype(np.uint64)


def _width(x: np.ndarray) -> int:
    return max(1, -(-int(x.max(initial=0)).bit_length() // 8))


def _offsets(column: pa.Array) -> np.ndarray:
    return np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1]


def _flat(column: pa.Array) -> np.ndarray:
    """The bytes of all values of a binary column, end to end."""
    ends = _offsets(column)
    return np.frombuffer(column.buffers()[2], np.uint8)[ends[0] : ends[-1]] if ends[-1] > ends[0] else np.zeros(0, np.uint8)


def _starts(size: np.ndarray) -> np.ndarray:
    return np.cumsum(size) - size


class FirstIds:
    """A set of ids as bitmaps."""

    def __init__(self, chunks: np.ndarray, maps: list[bytes]):
        self.chunks = chunks
        self.bits = np.frombuffer(b"".join(maps), np.uint8).reshape(len(maps), MAP_IDS // 8)

    def has(self, ids: np.ndarray) -> np.ndarray:
        if not self.chunks.size:
            return np.zeros(ids.size, bool)
        at = np.minimum(np.searchsorted(self.chunks, ids // MAP_IDS), self.chunks.size - 1)
        place = ids % MAP_IDS
        return (self.chunks[at] == ids // MAP_IDS) & ((self.bits[at, place >> 3] >> (place & 7).astype(np.uint8) & 1) == 1)


def bitmaps(ids: DataFrame) -> FirstIds | None:
    """The set of ``ids(node)``, numbers from 0; None if it takes more than ``MOST_MAPS`` bitmaps."""
    chunk = F.expr(f"node div {MAP_IDS}").alias("chunk")
    if ids.select(chunk).distinct().count() > MOST_MAPS:
        return None
    found = ids.groupBy(chunk).agg(F.bitmap_construct_agg(F.col("node") % MAP_IDS).alias("bits")).toArrow()
    chunks = found["chunk"].to_numpy()
    order = np.argsort(chunks)
    maps = found["bits"].to_pylist()
    return FirstIds(chunks[order], [maps[i] for i in order])


def frequent(met: DataFrame, most: int = MOST_KEYS) -> tuple[DataFrame, np.ndarray]:
    """Keys of ``met(key, count)``, as a table and sorted: all of them, or those of the largest counts as far as ``most`` go."""
    counts = sorted(map(tuple, met.groupBy("count").agg(F.count("*").alias("keys")).collect()), reverse=True)
    kept = np.flatnonzero(np.cumsum([n for _, n in counts]) <= most)
    if not kept.size:
        return met.select("key").limit(0), np.zeros(0, np.uint64)
    found = met.filter(F.col("count") >= counts[kept[-1]][0]).select("key")
    return found, np.sort(found.toArrow()["key"].to_numpy().astype(np.uint64))


def _among(keys: np.ndarray, many: np.ndarray) -> np.ndarray:
    return many[np.minimum(np.searchsorted(many, keys), many.size - 1)] == keys if many.size else np.zeros(keys.size, bool)


def _counting(held: np.ndarray, carried: np.ndarray) -> np.ndarray:
    """Of the places of lists end to end, those that are among the first ``carried`` of their list."""
    return np.arange(held.sum()) - np.repeat(_starts(held), held) < np.repeat(carried, held)


def _chosen(keys: np.ndarray, held: np.ndarray, carried: np.ndarray, many: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where a list holds ``held`` keys in order, of which the first ``carried`` count: the places of those that count once ``many`` have
    moved to the end of their lists, and whether they are new (they did not count before, or are one of ``many``)."""
    before, often = _counting(held, carried), _among(keys, many)
    order = np.argsort(np.repeat(np.arange(held.size), held) * 2 + often, kind="stable")
    now = np.zeros(keys.size, bool)
    now[order] = before
    at = np.flatnonzero(now)
    return at, (~before | often)[at]


def _packed(keys: np.ndarray, row: np.ndarray, nodes: np.ndarray, new: bool, bits: int) -> pa.RecordBatch:
    """One block per bucket of keys that the rows ``row`` of ``nodes`` carry."""
    both = np.sort(keys << np.uint64(24) | row.astype(np.uint64))
    keys, node = both >> np.uint64(24), nodes[(both & np.uint64((1 << 24) - 1)).astype(np.int64)]
    shift = np.uint64(8 * KEY_BYTES - bits)
    bucket = keys >> shift
    first = np.flatnonzero(np.append(True, bucket[1:] != bucket[:-1]))
    gaps = np.diff(keys, prepend=np.uint64(0))
    gaps[first] = keys[first] & np.uint64((1 << int(shift)) - 1)
    base = int(nodes.min())
    away = (node - base).astype(np.uint64)
    columns: list[list] = [[], [], [], [], [], [], []]
    for lo, hi in zip(first.tolist(), [*first[1:].tolist(), keys.size], strict=True):
        a, b = _width(gaps[lo:hi]), _width(away[lo:hi])
        for column, x in zip(columns, (int(bucket[lo]), base, new, a, b, low_bytes(gaps[lo:hi], a).tobytes(), low_bytes(away[lo:hi], b).tobytes()), strict=True):
            column.append(x)
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, _BLOCK, strict=True)], schema=_BLOCK)


def _runs(nodes: np.ndarray, keys: np.ndarray) -> Iterator[tuple[int, int]]:
    """Ranges of rows of about ``STEP`` keys, of ids from one partition where these lie together: ids far apart take more bytes."""
    far = np.flatnonzero(np.diff(nodes >> 33)) + 1
    cuts = far.tolist() if far.size < 8 else []
    for lo, hi in zip([0, *cuts], [*cuts, nodes.size], strict=True):
        ends = np.cumsum(keys[lo:hi])
        done = 0
        while lo < hi:
            to = max(lo + 1, hi - ends.size + int(np.searchsorted(ends, done + STEP, side="right")))
            yield lo, to
            done, lo = int(ends[to - 1 - (hi - ends.size)]), to


def meetings(rows: DataFrame, first: FirstIds | None = None, many: np.ndarray | None = None) -> DataFrame:
    """``(key, node, center, new)`` of ``rows(node, keys, held, carried)`` where two or more rows carry an equal key; ``center`` is one of
    them, the smallest where rows come in order.

    ``keys`` has lists of ``held`` keys end to end, ``KEY_BYTES`` bytes each; the first ``carried`` of each list count. With ``many``, a
    sorted array, only rows of which one of these keys counts take part: they move them to the end of their lists, all that the lists
    hold and not only those that counted, so that the order of keys is one for all rows. ``new`` tells which keys count since. Of rows
    given with ``first``, only its ids take part.
    """
    context = rows.sparkSession.sparkContext
    only, often = (None if x is None else context.broadcast(x) for x in (first, many))
    total = rows.select(F.sum(F.aggregate("carried", F.lit(0).cast("long"), lambda a, x: a + x))).first()[0] or 0
    bits = max(LEAST_BITS, min(8 * KEY_BYTES - 1, (int(total) // BUCKET).bit_length()))

    def pack(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if only is not None:
                b = b.filter(pa.array(only.value.has(b.column(0).to_numpy())))
            if not b.num_rows:
                continue
            nodes = b.column(0).to_numpy()
            per_row = np.diff(_offsets(b.column(1))).astype(np.int64) // KEY_BYTES
            for lo, hi in _runs(nodes, per_row):
                part = b.slice(lo, hi - lo)
                keys = from_bytes(_flat(part.column(1)), KEY_BYTES)
                held, carried = (part.column(i).flatten().to_numpy().astype(np.int64) for i in (2, 3))
                row = np.repeat(np.arange(hi - lo), per_row[lo:hi])
                if often is None:
                    at = np.flatnonzero(_counting(held, carried))
                    new = np.zeros(at.size, bool)
                else:
                    late = np.bincount(row[_counting(held, carried) & _among(keys, often.value)], minlength=hi - lo) > 0
                    lists = np.repeat(late, np.diff(part.column(2).offsets.to_numpy()))
                    keys, row = keys[late[row]], row[late[row]]
                    at, new = _chosen(keys, held[lists], carried[lists], often.value)
                for kind in (False, True):
                    some = at[new == kind]
                    if some.size:
                        yield _packed(keys[some], row[some], nodes[lo:hi], kind, bits)

    blocks = rows.select("node", "keys", "held", "carried").mapInArrow(pack, _BLOCK_SQL)
    blocks = blocks.repartition("bucket").sortWithinPartitions("bucket", "base")
    return blocks.mapInArrow(lambda batches: _met(batches, bits), _MEETING_SQL)


def _met(batches: Iterable[pa.RecordBatch], bits: int) -> Iterator[pa.RecordBatch]:
    """Rows of equal keys, from blocks in the order of their buckets."""
    bucket, waiting = -1, 0
    held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    # One row of each key so far: key, node, new, and whether it was given out.
    none = (np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, bool), np.zeros(0, bool))
    kept = none

    def settle() -> Iterator[pa.RecordBatch]:
        nonlocal kept, waiting
        if not held:
            return
        key, node, new = (np.concatenate([k, *x]) for k, x in zip(kept[:3], zip(*held, strict=True), strict=True))
        told = np.append(kept[3], np.zeros(key.size - kept[3].size, bool))
        held.clear()
        waiting = 0
        order = np.argsort(key, kind="stable")
        key, node, new, told = key[order], node[order], new[order], told[order]
        start = np.flatnonzero(np.append(True, key[1:] != key[:-1]))
        size = np.diff(np.append(start, key.size))
        center = np.repeat(node[start], size)
        out = np.flatnonzero(np.repeat(size > 1, size) & ~told)
        kept = key[start], node[start], new[start], told[start] | (size > 1)
        for lo in range(0, out.size, 1 << 17):
            at = out[lo : lo + (1 << 17)]
            yield pa.RecordBatch.from_arrays([pa.array(key[at].astype(np.int64)), pa.array(node[at]), pa.array(center[at]), pa.array(new[at])], names=["key", "node", "center", "new"])

    for b in batches:
        for i in range(b.num_rows):
            x = {f.name: b.column(j)[i] for j, f in enumerate(_BLOCK)}
            if x["bucket"].as_py() != bucket:
                yield from settle()
                bucket, kept = x["bucket"].as_py(), none
            gaps, away = (from_bytes(np.frombuffer(x[c].as_buffer(), np.uint8), x[w].as_py()) for c, w in (("keys", "key_width"), ("nodes", "node_width")))
            key = np.cumsum(gaps, dtype=np.uint64) + (np.uint64(bucket) << np.uint64(8 * KEY_BYTES - bits))
            held.append((key, away.astype(np.int64) + x["base"].as_py(), np.full(key.size, x["new"].as_py())))
            waiting += key.size
            if waiting >= STEP:
                yield from settle()
    yield from settle()
