"""Groups by packed blocks against groups by plain dictionaries."""

import random
from collections import Counter, defaultdict

import numpy as np

from transitlens.llm import key_groups
from transitlens.llm.key_groups import KEY_BYTES, bitmaps, frequent, low_bytes, meetings

draw = random.Random(11)
NODES = [i + (i % 3 << 33) for i in range(120)]
OFTEN = [draw.getrandbits(40) for _ in range(6)]


def table(spark, lists, carried):
    rows = [(n, low_bytes(np.array([k for x in found for k in x], np.uint64), KEY_BYTES).tobytes(), [len(x) for x in found], [min(carried, len(x)) for x in found]) for n, found in lists.items()]
    return spark.createDataFrame(rows, "node long, keys binary, held array<int>, carried array<int>").repartition(3)


def random_lists():
    keys = [draw.getrandbits(40) for _ in range(300)] + [0, (1 << 40) - 1]
    # The last bit is the band, so that the lists of a row share no key.
    return {n: [[k >> 1 << 1 | band for k in draw.sample(OFTEN, draw.randint(0, 3)) + draw.sample(keys, draw.randint(0, 9))] for band in range(draw.randint(0, 2))] for n in NODES}


def groups(counting):
    found = defaultdict(set)
    for n, keys in counting.items():
        for k in keys:
            found[k].add(n)
    return {k: v for k, v in found.items() if len(v) > 1}


def got(frame):
    rows, found, centers = frame.collect(), defaultdict(set), defaultdict(set)
    assert len({(r.key, r.node, r.new) for r in rows}) == len(rows)
    for r in rows:
        found[r.key].add(r.node)
        centers[r.key].add(r.center)
    assert all(len(c) == 1 and c <= found[k] for k, c in centers.items())
    return found, rows


def test_meetings_and_moved_keys(spark, monkeypatch):
    monkeypatch.setattr(key_groups, "STEP", 40)  # many runs of a batch, many steps of a bucket
    lists = random_lists()
    rows = table(spark, lists, 4)
    before = {n: {k for x in found for k in x[:4]} for n, found in lists.items()}
    want = groups(before)
    assert got(meetings(rows))[0] == want
    some = bitmaps(spark.createDataFrame([(n,) for n in NODES[::2]], "node long"))
    assert got(meetings(rows, some))[0] == groups({n: before[n] for n in NODES[::2]})

    counts = Counter({k: len(v) for k, v in want.items() if len(v) > 8})
    assert counts
    many = frequent(spark.createDataFrame(list(counts.items()), "key long, count long"))[1]
    assert many.tolist() == sorted(counts)
    top = frequent(spark.createDataFrame([(1, 30), (2, 20), (3, 10), (4, 10)], "key long, count long"), most=3)[1]
    assert top.tolist() == [1, 2]
    late = {n for n in NODES if before[n] & set(counts)}
    now = {n: [k for x in lists[n] for k in ([k for k in x if k not in counts] + [k for k in x if k in counts])[:4]] for n in late}
    found, told = got(meetings(rows, None, many))
    assert found == groups(now)
    old = {(n, k) for n in NODES for x in lists[n] for k in x[:4]}
    assert all(r.new == ((r.node, r.key) not in old or r.key in counts) for r in told)
