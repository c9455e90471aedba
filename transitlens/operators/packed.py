"""Lists of ids as bytes, a third of their size as arrays, for shuffles that carry a list a row.

The ids of a list come in a few ranks: those that count for the smallest k, those that the next one adds, and so on. Within a rank they are
sorted; its first id is stored as it is, every other one as its distance from the one before, in groups of seven bits.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa


def _starts(size: np.ndarray) -> np.ndarray:
    return np.cumsum(size) - size


def pack(size: np.ndarray, ids: np.ndarray, d2: np.ndarray, ks: tuple[int, ...]) -> tuple[pa.Array, pa.Array]:
    """``(packed, n)`` of lists end to end, of so many distinct ``ids`` each, nearest first: for each of ``ks`` how many ids are no
    farther than the k-th (the last, with fewer); and the bytes of all of them, the ranks in order."""
    size = size.astype(np.int64)
    row, start = np.repeat(np.arange(len(size)), size), _starts(size)
    n = np.zeros((len(size), len(ks)), np.int32)
    some = size > 0
    for i, k in enumerate(ks):
        last = np.zeros(len(size), np.int64)
        last[some] = d2[(start + np.minimum(size, k) - 1)[some]]
        n[:, i] = np.bincount(row[d2 <= last[row]], minlength=len(size))
    at, rank = np.arange(len(row)) - start[row], np.zeros(len(row), np.int8)
    for i in range(len(ks)):
        rank += at >= n[row, i]
    by = np.lexsort((ids, rank, row))
    ids, rank = ids[by], rank[by]
    first = np.ones(len(row), bool)
    first[1:] = (row[1:] != row[:-1]) | (rank[1:] != rank[:-1])
    code = np.zeros(len(row), np.uint64)
    code[1:] = np.diff(ids).view(np.uint64)
    code[first] = (ids[first] << 1 ^ ids[first] >> 63).view(np.uint64)
    width = np.ones(len(row), np.int64)
    for j in range(1, 10):
        width += code >> np.uint64(7 * j) > 0
    ends = np.cumsum(width)
    out = np.zeros(int(ends[-1]) if len(ends) else 0, np.uint8)
    for j in range(int(width.max(initial=0))):
        has = np.flatnonzero(width > j)
        out[ends[has] - width[has] + j] = (code[has] >> np.uint64(7 * j) & np.uint64(127)).astype(np.uint8) | ((width[has] > j + 1).astype(np.uint8) << 7)
    offsets = np.concatenate([[0], ends])[np.concatenate([[0], np.cumsum(size)])].astype(np.int32)
    packed = pa.Array.from_buffers(pa.binary(), len(size), [None, pa.py_buffer(offsets), pa.py_buffer(out)])
    return packed, pa.ListArray.from_arrays(pa.array(np.arange(len(size) + 1) * len(ks), pa.int32()), pa.array(n.ravel()))


def unpack(packed: pa.Array, n: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """``(size, ids)`` of what :func:`pack` gave: ranks in order, sorted within."""
    offsets = np.frombuffer(packed.buffers()[1], np.int32)[packed.offset : packed.offset + len(packed) + 1].astype(np.int64) if len(packed) else np.zeros(1, np.int64)
    raw = np.frombuffer(packed.buffers()[2], np.uint8)[offsets[0] : offsets[-1]] if offsets[-1] > offsets[0] else np.zeros(0, np.uint8)
    ends = np.flatnonzero(raw < 128)
    size = np.diff(np.searchsorted(ends, offsets - offsets[0]))
    if not len(ends):
        return size, np.zeros(0, np.int64)
    begin = np.concatenate([[0], ends[:-1] + 1])
    width = ends - begin + 1
    code = np.zeros(len(ends), np.uint64)
    for j in range(int(width.max())):
        has = np.flatnonzero(width > j)
        code[has] |= (raw[begin[has] + j] & np.uint8(127)).astype(np.uint64) << np.uint64(7 * j)
    first, start = np.zeros(len(ends) + 1, bool), _starts(size)
    first[start] = True
    counts = n.value_lengths().to_numpy(zero_copy_only=False)
    which, upto = np.repeat(np.arange(len(size)), counts), n.flatten().to_numpy()
    inside = upto < size[which]
    first[(start[which] + upto)[inside]] = True
    first = np.flatnonzero(first[:-1])
    whole = code[first]
    value = code.view(np.int64)
    value[first] = (whole >> np.uint64(1)).view(np.int64) ^ -(whole & np.uint64(1)).view(np.int64)
    total = np.cumsum(value)
    before = total[first] - value[first]
    return size, total - np.repeat(before, np.diff(np.append(first, len(value))))
