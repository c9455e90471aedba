"""The worked planning example, the counterexample to the published dominance rule, and search against enumeration."""

import random

import pytest

from transitlens.operators import graph
from transitlens.operators.planner import Network, Points, best_by_enumeration, candidate_paths, corridors, paths_within, plan_routes, search
from transitlens.schema import ROUTE_POINTS

EDGES = "ab16 ac10 ad10 be15 ce16 cf15 df23 fh14 eh14 hj15 ej23".split()
WON = "a1o b1d c1d c3o c4o d5o e2o f2o f3d f4d g5o h2d i6o j6d".split()


def example() -> Network:
    net = Network()
    for e in EDGES:
        u, v, n = ord(e[0]), ord(e[1]), int(e[2:])
        net.near.setdefault(u, []).append((v, n))
        net.near.setdefault(v, []).append((u, n))
    for w in WON:
        net.won[ord(w[0])] = net.won.get(ord(w[0]), Points()) | {(int(w[1]), 1 if w[2] == "o" else 2)}
    return net


def name(plan):
    return "".join(map(chr, plan.path))


@pytest.mark.parametrize(("objective", "mode", "path", "length", "value"), [("max", "any", "acej", 49, 5), ("max", "both", "acfhj", 54, 4), ("min", "any", "abej", 54, 3)])
def test_worked_example(objective, mode, path, length, value):
    for find in (search, best_by_enumeration):
        p = find(example(), ord("a"), ord("j"), 60, objective, mode)
        assert (name(p), p.length, p.value) == (path, length, value)


def test_candidates_of_the_example():
    found = {"".join(map(chr, p)): n for n, p in paths_within(example(), ord("a"), ord("j"), 60)}
    assert found == {"acej": 49, "acfhj": 54, "acehj": 55, "abej": 54, "abehj": 60}


def test_no_path_within_the_limit():
    assert search(example(), ord("a"), ord("j"), 40) is None
    assert best_by_enumeration(example(), ord("a"), ord("j"), 40) is None


def counterexample() -> Network:
    net = Network()
    for u, v, n in (("s", "a", 1), ("a", "v", 1), ("s", "b", 2), ("b", "v", 1), ("v", "c", 1), ("c", "e", 1)):
        net.near.setdefault(ord(u), []).append((ord(v), n))
    both = Points({(1, 1), (1, 2), (2, 1), (2, 2)})
    net.won = {ord("a"): both, ord("c"): both, ord("b"): Points({(3, 1), (3, 2)})}
    return net


def test_published_rule_loses_the_optimum_and_containment_keeps_it():
    args = (counterexample(), ord("s"), ord("e"), 6, "max", "any")
    assert search(*args, dominance="count").value == 2
    assert search(*args, dominance="contain").value == best_by_enumeration(*args).value == 3


def random_network(draw, directed):
    net = Network()
    for u in range(6):
        for v in range(u + 1, 6):
            for a, b in ((u, v), (v, u)) if directed else ((u, v),):
                if draw.random() < 0.6:
                    n = draw.randint(1, 5)
                    net.near.setdefault(a, []).append((b, n))
                    if not directed:
                        net.near.setdefault(b, []).append((a, n))
    net.won = {v: Points({(draw.randint(1, 4), draw.randint(1, 2)) for _ in range(draw.randint(0, 4))}) for v in range(6)}
    return net


@pytest.mark.parametrize("objective", ["max", "min"])
@pytest.mark.parametrize("mode", ["any", "both"])
@pytest.mark.parametrize("directed", [False, True])
def test_search_equals_enumeration_on_random_networks(objective, mode, directed):
    draw = random.Random(5)
    with_bound = without = 0
    for _ in range(150):
        net = random_network(draw, directed)
        a, b = search(net, 0, 5, 9, objective, mode), best_by_enumeration(net, 0, 5, 9, objective, mode)
        assert (a is None) == (b is None)
        if a:
            assert (a.value, a.length, a.path) == (b.value, b.length, b.path)
            with_bound += a.labels
            without += search(net, 0, 5, 9, objective, mode, bound=False).labels
    assert with_bound < without


def test_a_longer_way_may_win_more_in_a_directed_network():
    net = Network({1: [(2, 1), (3, 1)], 2: [(9, 1)], 3: [(4, 1)], 4: [(5, 1)], 5: [(9, 1)]}, {2: Points({(1, 1)}), 4: Points({(2, 1)}), 5: Points({(3, 1)})})
    assert search(net, 1, 9, 10).value == best_by_enumeration(net, 1, 9, 10).value == 2


@pytest.fixture(scope="module")
def diagonal(spark):
    """Stops a metre and a half apart: every edge rounds to one metre, so paths look shorter than the straight line."""
    points = spark.createDataFrame([(1, i + 1, i, 5000 + i, 5000 + i) for i in range(101)], ROUTE_POINTS)
    return points, graph.build(points)


def test_corridors_hold_every_path_of_short_edges(spark, diagonal):
    points, edges = diagonal
    asked = spark.createDataFrame([(1, 0, 100, 100)], "query_id long, src long, dst long, max_len_m long")
    stops = points.select("stop_id", "x_m", "y_m")
    assert corridors(asked, edges, stops).count() == 200
    omega = spark.createDataFrame([(50, 7, 3)], "stop_id long, transition_id long, mask int")
    got = plan_routes(asked, edges, stops, omega).collect()
    assert [(r.length_m, r.n_transitions, r.n_stops) for r in got] == [(100, 1, 101)]
    assert [r.nth for r in candidate_paths(asked, edges, stops).collect()] == [0]


def test_shortest_distances_and_lengths(spark, diagonal):
    points, edges = diagonal
    got = {r.src: r.length_m for r in graph.shortest_to(edges, spark.createDataFrame([(10,)], "target long"), 5).collect()}
    assert got == {i: abs(i - 10) for i in range(5, 16)}
    assert graph.path_length(points).first()[1:] == (100, 101)
    one_way = graph.build(points, directed=True)
    assert one_way.count() == 100 and graph.build(points.limit(0)).count() == 0


def test_candidates_beyond_the_limit_are_an_error(spark):
    edges = spark.createDataFrame([(a, b, 1) for a in range(5) for b in range(5) if a != b], "src long, dst long, length_m long")
    stops = spark.createDataFrame([(i, i, 0) for i in range(5)], "stop_id long, x_m long, y_m long")
    asked = spark.createDataFrame([(1, 0, 4, 4)], "query_id long, src long, dst long, max_len_m long")
    assert candidate_paths(asked, edges, stops).count() == 16
    with pytest.raises(Exception, match="more than 3 paths"):
        candidate_paths(asked, edges, stops, 3).count()
