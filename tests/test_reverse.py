"""Reverse queries against a brute-force version on a small plane, with ties, shared stops and excluded routes."""

import random

import pytest

from transitlens.operators.reverse import query_frame, reverse_routes
from transitlens.schema import ENDPOINTS, ROUTE_POINTS

draw = random.Random(3)
ROUTES = [(r, i, 0, draw.randrange(0, 30) * 500, draw.randrange(0, 30) * 500) for r in range(1, 13) for i in range(1, 6)]
ROUTES = [(r, i, x * 100_000 + y, x, y) for r, i, _, x, y in ROUTES]
POINTS = [(t, s, draw.randrange(-2000, 17000), draw.randrange(-2000, 17000)) for t in range(120) for s in "od"]
QUERY = [(2000, 2000), (5000, 6000), (9000, 8000)]


def d2(a, b):
    return (a[0] - b[0]) ** 2 + (a[1] - b[1]) ** 2


def brute(k, mode, exclude=None):
    sides = {}
    for t, s, x, y in POINTS:
        dq = min(d2((x, y), q) for q in QUERY)
        nearer = {r for r, _, _, rx, ry in ROUTES if r != exclude and d2((x, y), (rx, ry)) < dq}
        if len(nearer) < k:
            sides[t] = sides.get(t, 0) | (1 if s == "o" else 2)
    return {(t, m) for t, m in sides.items() if mode == "any" or m == 3}


@pytest.fixture(scope="module")
def tables(spark):
    routes = spark.createDataFrame(ROUTES, ROUTE_POINTS).persist()
    points = spark.createDataFrame([(*p, None) for p in POINTS], ENDPOINTS).persist()
    return routes, points


@pytest.mark.parametrize("method", ["forward", "scan", "framework", "cell", "split"])
def test_methods_equal_brute_force(spark, tables, method):
    for k, mode, exclude in ((1, "any", None), (3, "both", 4)):
        got = reverse_routes(*tables, query_frame(spark, QUERY, 0, exclude), k, mode, method=method)
        assert {(r.transition_id, r["mask"]) for r in got.collect()} == brute(k, mode, exclude)


def test_more_neighbours_than_routes_gives_all(spark, tables):
    assert reverse_routes(*tables, query_frame(spark, QUERY), 13).count() == 120


def test_options_do_not_change_the_result(spark, tables):
    for options in ({"order": "coverage"}, {"credit": "single"}, {"points": False}, {"descend_routes": True}):
        got = reverse_routes(*tables, query_frame(spark, QUERY), 2, **options)
        assert {(r.transition_id, r["mask"]) for r in got.collect()} == brute(2, "any")


def test_bad_arguments(spark, tables):
    with pytest.raises(ValueError):
        query_frame(spark, [])
    with pytest.raises(ValueError):
        reverse_routes(*tables, query_frame(spark, QUERY), 0)
