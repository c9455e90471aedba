"""Lists of routes as bytes: what goes in comes out, and how many bytes it takes."""

import random

import numpy as np
import pyarrow as pa

from transitlens.operators.packed import pack, unpack


def _brute(lists, ks):
    out = []
    for ids, d2 in lists:
        n = [sum(v <= d2[min(k, len(d2)) - 1] for v in d2) for k in ks] if d2 else [0] * len(ks)
        want, done = [], 0
        for m in sorted(set(n)):
            want += sorted(ids[done:m])
            done = m
        out.append((n, want + sorted(ids[done:])))
    return out


def test_packed_lists_come_back_by_rank():
    draw = random.Random(1)
    lists = [([], []), ([0], [5]), ([-(1 << 63), (1 << 63) - 1, 7], [1, 1, 2]), ([(1 << 63) - 1, -(1 << 63)], [1, 2])]
    for _ in range(300):
        ids = draw.sample(range(-500, 400_000), draw.randrange(40))
        lists.append((ids, sorted(draw.randrange(9) for _ in ids)))
    for ks in ((10,), (25, 1, 5), (1, 5, 10, 15, 20, 25)):
        flat = [np.array([v for x in lists for v in x[i]], np.int64) for i in (0, 1)]
        packed, n = pack(np.array([len(x[0]) for x in lists]), *flat, ks)
        for lo in (0, 2, len(lists)):
            size, ids = unpack(packed.slice(lo), n.slice(lo))
            got = np.split(ids, np.cumsum(size)[:-1]) if len(size) else []
            assert [(a, b.tolist()) for a, b in zip(n.slice(lo).to_pylist(), got, strict=True)] == _brute(lists[lo:], ks)


def test_packed_lists_take_less_than_half_of_their_arrays():
    draw = np.random.default_rng(2)
    ids = np.concatenate([draw.choice(420_000, 28, replace=False) for _ in range(500)]).astype(np.int64)
    packed, _ = pack(np.full(500, 28), ids, np.ones(len(ids), np.int64), (10,))
    assert pa.compute.sum(pa.compute.binary_length(packed)).as_py() < 3 * len(ids)
