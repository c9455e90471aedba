"""Tiles of groups against all pairs, with components that fill many tiles."""

import random

import numpy as np
import pyarrow as pa
import pytest

from transitlens.llm import group_compare
from transitlens.llm.group_compare import near_in_groups, near_pairs

draw = random.Random(4)


def bits(x):
    return sum(bin(v & (2**64 - 1)).count("1") for v in x)


def folded(a, n):
    return [int(np.bitwise_xor.reduce(np.array(a, np.int64)[i::n])) for i in range(n)]


def apart(a, b):
    n = min(len(a), len(b))
    return bits([x ^ y for x, y in zip(folded(a, n), folded(b, n), strict=True)])


def members(n, components):
    base = [draw.getrandbits(62) for _ in range(4)]
    out = []
    for _ in range(n):
        s = list(base)
        for _ in range(draw.randint(0, 30)):
            s[draw.randrange(4)] ^= 1 << draw.randrange(62)
        size = draw.randint(100, 127)
        if draw.random() < 0.3:
            s, size = [*s, 0, 0, 0, 0], draw.randint(128, 150)
        out.append((draw.choice(components), size, s))
    return out


def brute(rows):
    found = set()
    for i, (c, n, s) in enumerate(rows):
        for j in range(i):
            c2, n2, s2 = rows[j]
            if c != c2 and 100 * n >= 80 * n2 and 100 * n2 >= 80 * n and apart(s, s2) <= (n + n2) * 20 // 180:
                found.add((j, i))
    return found


def test_pairs_of_a_task():
    rows = members(120, [1, 2, 3])
    arrays = [np.array(x) for x in zip(*((c, n) for c, n, _ in rows), strict=True)]
    sketch = pa.array([s for _, _, s in rows], pa.list_(pa.int64()))
    one = np.zeros(120, np.int64)
    i, j = near_pairs(one, one, np.ones(120, bool), arrays[0], arrays[1], sketch, np.zeros(120, bool), 80)
    assert set(zip(i.tolist(), j.tolist(), strict=True)) == brute(rows) and brute(rows)
    i, j = near_pairs(one, one, np.ones(120, bool), arrays[0], arrays[1], sketch, np.ones(120, bool), 80)
    offers = set(zip(i.tolist(), j.tolist(), strict=True))
    assert offers <= brute(rows) and len(offers) <= 3


@pytest.mark.parametrize("components", [[1], [1, 1, 1, 1, 2], [1, 2, 3], list(range(40))])
def test_tiles_equal_all_pairs(spark, monkeypatch, components):
    monkeypatch.setattr(group_compare, "TILE", 8)
    groups = {7: members(90, components), 8: members(5, [1, 2]), 9: members(8, [1, 2])}
    rows = [(key, 1000 * key + i, c, len(g), n, s, False) for key, g in groups.items() for i, (c, n, s) in enumerate(g)]
    table = spark.createDataFrame(rows, "key long, node long, component long, members long, size int, sketch array<long>, offer boolean")
    got = {(r.u, r.v) for r in near_in_groups(table, 80).collect()}
    assert got == {(1000 * key + i, 1000 * key + j) for key, g in groups.items() for i, j in brute(g)}
