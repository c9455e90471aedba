"""Route planning: the path between two stops, within a length limit, that serves the most or the fewest transitions.

A planning query only needs the stops through which a path of the allowed length can run. These corridors are cut out inside tasks, of
the stops in and around the tile that a query lies in, and its search runs there: tiles in parallel, a tile's queries in turn.

Defined cases: a query whose ends are not stops, or without a path within its limit, has no row; one whose ends are the same stop has
that stop as its path; edges may be one-way; repeated edges count with their least length; stops without results win nothing.
"""

from __future__ import annotations

import bisect
import heapq
from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from ..functions import geometry as G
from ..plans.layout import EndpointIndex, StopIndex
from ..plans.shared import written
from . import tiles
from .knn import stops_by_rings
from .reverse import result_counts, reverse_routes
from .verify import level_for

Points = frozenset  # of (transition, side)
RESULT = "query_id bigint, path string, length_m bigint, n_transitions bigint, n_stops bigint, labels bigint"


def served(points: Iterable[tuple[int, int]], mode: str) -> int:
    """Transitions won by one endpoint (any), or by both."""
    sides: dict[int, int] = {}
    for t, side in points:
        sides[t] = sides.get(t, 0) | side
    return sum(mode == "any" or m == 3 for m in sides.values())


def _distances(near: dict[int, list[tuple[int, int]]], start: int) -> dict[int, int]:
    """Shortest distances from a stop along ``near``."""
    best, heap = {start: 0}, [(0, start)]
    while heap:
        d, v = heapq.heappop(heap)
        if d > best[v]:
            continue
        for u, n in near.get(v, ()):
            if d + n < best.get(u, d + n + 1):
                best[u] = d + n
                heapq.heappush(heap, (d + n, u))
    return best


class Ceilings:
    """What a partial path can still win at most: all that the stops win through which it can run on to the target within the limit."""

    def __init__(self, net: Network, rest: dict[int, int]):
        self.net, self.rest = net, rest
        self.by_end: dict[int, tuple[list[int], list[int]]] = {}
        self.united: dict[tuple[int, int], Points] = {}

    def points(self, end: int, left: int) -> Points:
        """Of the stops that a path from ``end`` to the target of length ``left`` can pass."""
        if end not in self.by_end:
            need = sorted((d + self.rest[v], v) for v, d in self.net.distances_from(end).items() if v in self.rest and self.net.won.get(v))
            self.by_end[end] = [n for n, _ in need], [v for _, v in need]
        need, stops = self.by_end[end]
        n = bisect.bisect_right(need, left)
        if (end, n) not in self.united:
            self.united[end, n] = self.net.points(stops[:n])
        return self.united[end, n]


@dataclass
class Network:
    """A corridor: neighbours with lengths, and the endpoints each stop wins."""

    near: dict[int, list[tuple[int, int]]] = field(default_factory=dict)
    won: dict[int, Points] = field(default_factory=dict)

    def distances_to(self, target: int) -> dict[int, int]:
        into: dict[int, list[tuple[int, int]]] = {}
        for u, out in self.near.items():
            for v, n in out:
                into.setdefault(v, []).append((u, n))
        return _distances(into, target)

    def distances_from(self, source: int) -> dict[int, int]:
        return _distances(self.near, source)

    def points(self, path: Iterable[int]) -> Points:
        return frozenset().union(*(self.won.get(v, Points()) for v in path))


@dataclass(frozen=True)
class Plan:
    path: tuple[int, ...]
    length: int
    value: int
    labels: int


def _better(objective: str, a: Plan, b: Plan | None) -> bool:
    sign = -1 if objective == "max" else 1
    return b is None or (sign * a.value, a.length, a.path) < (sign * b.value, b.length, b.path)


def paths_within(net: Network, src: int, dst: int, limit: int) -> Iterator[tuple[int, tuple[int, ...]]]:
    """All loopless paths of at most the limit, shortest first."""
    rest = net.distances_to(dst)
    if rest.get(src, limit + 1) > limit:
        return
    heap = [(rest[src], 0, (src,))]
    while heap:
        _, done, path = heapq.heappop(heap)
        if path[-1] == dst:
            yield done, path
            continue
        for v, n in net.near.get(path[-1], ()):
            if v not in path and v in rest and done + n + rest[v] <= limit:
                heapq.heappush(heap, (done + n + rest[v], done + n, (*path, v)))


def all_paths(net: Network, src: int, dst: int, limit: int, won: dict[int, int] | None = None) -> Iterator[tuple[int, tuple[int, ...], int]]:
    """The paths of :func:`paths_within` in no order, depth first, each with the bits of ``won`` of its stops united on the way."""
    rest, won = net.distances_to(dst), won or {}
    if rest.get(src, limit + 1) > limit:
        return
    if src == dst:
        yield 0, (src,), won.get(src, 0)
        return
    ahead: dict[int, list[tuple[int, int, int]]] = {}

    def steps(v: int) -> Iterator[tuple[int, int, int]]:
        if v not in ahead:
            ahead[v] = sorted((n + rest[u], n, u) for u, n in net.near.get(v, ()) if u in rest)
        return iter(ahead[v])

    none = (limit + 1, 0, 0)
    path, seen, lengths, bits, left = [src], {src}, [0], [won.get(src, 0)], [steps(src)]
    while left:
        least, n, v = next(left[-1], none)
        if lengths[-1] + least > limit:  # nor do the steps after it fit
            seen.remove(path.pop())
            for stack in (lengths, bits, left):
                stack.pop()
        elif v == dst:
            yield lengths[-1] + n, (*path, v), bits[-1] | won.get(v, 0)
        elif v not in seen:
            path.append(v)
            seen.add(v)
            lengths.append(lengths[-1] + n)
            bits.append(bits[-1] | won.get(v, 0))
            left.append(steps(v))


def best_by_enumeration(net: Network, src: int, dst: int, limit: int, objective: str = "max", mode: str = "any") -> Plan | None:
    """The baseline over stored results: each candidate's stops united, two bits a transition."""
    place: dict[int, int] = {}
    won: dict[int, int] = {}
    for v, points in net.won.items():
        won[v] = sum(1 << 2 * place.setdefault(t, len(place)) + side - 1 for t, side in points)
    first, sign = (4 ** len(place) - 1) // 3, -1 if objective == "max" else 1
    best, n = None, 0
    for length, path, bits in all_paths(net, src, dst, limit, won):
        n += 1
        value = ((bits | bits >> 1 if mode == "any" else bits & bits >> 1) & first).bit_count()
        if best is None or (sign * value, length, path) < best:
            best = sign * value, length, path
    return best and Plan(best[2], best[1], sign * best[0], n)


def _beats(a: tuple, b: tuple, objective: str, dominance: str, simple: bool) -> bool:
    """Whether label a makes label b of the same stop needless; labels are (length, path, points)."""
    if dominance == "count":  # the published rule, a heuristic
        if objective == "max":
            return a[0] < b[0] and served(a[2], "both") > served(b[2], "any")
        return a[0] > b[0] and served(a[2], "any") < served(b[2], "both")
    if a[0] > b[0]:
        return False
    if objective == "min":
        fine = a[2] <= b[2]
    else:
        fine = a[2] >= b[2] and (not simple or set(a[1]) <= set(b[1]))
    # Of equally long labels the first path in order stays, so that ties of whole paths end as enumeration ends them.
    return fine and (a[0] < b[0] or a[1] < b[1])


def search(net: Network, src: int, dst: int, limit: int, objective: str = "max", mode: str = "any", dominance: str = "contain", path_mode: str = "simple", bound: bool = True) -> Plan | None:
    """Label search: a partial path stays if the target is in reach, no label of its end beats it, and its bound can still win."""
    simple = path_mode == "simple"
    rest = net.distances_to(dst)
    if rest.get(src, limit + 1) > limit:
        return None
    ceilings = Ceilings(net, rest)
    first = (0, (src,), net.won.get(src, Points()))
    heap, table, best, n = [first[:2]], {src: [first]}, None, 1
    held = {first[1]: first}
    while heap:
        _, path = heapq.heappop(heap)
        label = held.pop(path, None)
        if label is None:  # beaten meanwhile
            continue
        length, _, points = label
        if path[-1] == dst:
            plan = Plan(path, length, served(points, mode), n)
            best = plan if _better(objective, plan, best) else best
            if simple:
                continue
        for v, step in net.near.get(path[-1], ()):
            if simple and v in path or v not in rest or length + step + rest[v] > limit:
                continue
            new = (length + step, (*path, v), points | net.won.get(v, Points()))
            if best is not None and objective == "min" and bound and served(new[2], mode) > best.value:
                continue
            if best is not None and objective == "max" and bound and served(new[2] | ceilings.points(v, limit - new[0]), mode) < best.value:
                continue
            if dominance != "none":
                rows = table.setdefault(v, [])
                if any(_beats(old, new, objective, dominance, simple) for old in rows):
                    continue
                for old in [r for r in rows if _beats(new, r, objective, dominance, simple)]:
                    rows.remove(old)
                    held.pop(old[1], None)
                rows.append(new)
            n += 1
            held[new[1]] = new
            heapq.heappush(heap, new[:2])
    return best and Plan(best.path, best.length, best.value, n)


def vertex_omega(stops: StopIndex, endpoints: EndpointIndex, ks: tuple[int, ...] = (10,), only: DataFrame | None = None, method: str = "rings") -> DataFrame:
    """``(k, stop_id, transition_id, mask)``: each stop (or those of ``only(stop_id)``) as a query of its own, for all k at once.

    ``rings`` finds for each endpoint how far its k-th nearest route is, and the stops within; work follows the stops around the
    endpoints. ``queries`` asks each stop as a reverse query, which reads what lies around the stops asked for only.
    """
    if method == "rings":
        at = stops_by_rings(endpoints.points, stops, ks)
        at = at if only is None else at.join(only.select("stop_id").distinct(), "stop_id", "left_semi")
        return at.groupBy("k", "stop_id", "transition_id").agg(F.bit_or(F.when(F.col("side") == "o", 1).otherwise(2)).alias("mask"))
    wanted = stops.points() if only is None else stops.points().join(only.select("stop_id").distinct(), "stop_id", "left_semi")
    queries = wanted.select(F.col("stop_id").alias("query_id"), F.lit(0).alias("q_idx"), "x_m", "y_m", F.lit(None).cast("bigint").alias("exclude_route_id"))
    counts = result_counts(stops, endpoints, queries, max(ks), "split")
    at = counts.withColumn("k", F.explode(F.array(*map(F.lit, ks)))).filter(F.col("nearer") < F.col("k"))
    return at.groupBy("k", F.col("query_id").alias("stop_id"), "transition_id").agg(F.bit_or(F.when(F.col("side") == "o", 1).otherwise(2)).alias("mask"))


def path_omega(paths: DataFrame, omega: DataFrame, mode: str = "any") -> DataFrame:
    """``paths(query_id, stop_id)`` to ``(query_id, transition_id, mask)``: stored results of the stops united, then the mode."""
    united = paths.join(omega, "stop_id").groupBy("query_id", "transition_id").agg(F.bit_or("mask").alias("mask"))
    return united if mode == "any" else united.filter("mask = 3")


def corridors(queries: DataFrame, edges: DataFrame, stops: DataFrame) -> DataFrame:
    """``(query_id, src, dst, max_len_m, u, v, length_m)``: edges on which a path of the query can run.

    An edge of length n, rounded, spans at most n + 0.5, so at most ``1 + 0.5 / least`` times its length, ``least`` being the shortest
    edge: straight distances, with that factor, bound travel distances from below and the corridor holds every path. It lies in a square
    around the middle of both ends, of which a few cells of suitable width are looked at.
    """
    ends = stops.select("stop_id", "x_m", "y_m")
    q = _reaches(queries, edges, ends)
    q = q.withColumn("level", level_for(F.col("reach"), 0.5))
    for axis in "xy":
        middle = F.expr(f"(src_at.{axis}_m + dst_at.{axis}_m) div 2")
        half = F.expr("reach div 2 + 1")
        q = q.withColumn(f"g{axis}", F.explode(F.sequence(G.grid(middle - half, F.col("level")), G.grid(middle + half, F.col("level")))))
    q = q.withColumn("cell", G.grid_cell(F.col("gx"), F.col("gy"))).drop("gx", "gy")
    at = F.explode(F.array(*(F.struct(F.lit(s).alias("level"), G.cell_at(F.col("x_m"), F.col("y_m"), s).alias("cell")) for s in G.LEVELS)))
    placed = ends.withColumn("_at", at).select("*", "_at.level", "_at.cell").drop("_at")

    def straight(p: str) -> Column:
        return F.sqrt(((F.col("x_m") - F.col(f"{p}.x_m")) ** 2 + (F.col("y_m") - F.col(f"{p}.y_m")) ** 2).cast("double"))

    inside = q.join(placed, ["level", "cell"]).filter(straight("src_at") + straight("dst_at") <= F.col("reach"))
    inside = inside.select("query_id", "src", "dst", "max_len_m", F.col("stop_id").alias("u"))
    both = inside.join(edges.select(F.col("src").alias("u"), F.col("dst").alias("v"), "length_m"), "u")
    return both.join(inside.select("query_id", F.col("u").alias("v")), ["query_id", "v"])


def plan_routes(queries: DataFrame, edges: DataFrame, stops: DataFrame, omega: DataFrame, objective: str = "max", mode: str = "any", method: str = "search", dominance: str = "contain", path_mode: str = "simple") -> DataFrame:
    """The best path of each of ``queries(query_id, src, dst, max_len_m)`` over ``omega(stop_id, transition_id, mask)``.

    ``search`` is the label search, ``pre`` the enumeration over stored results, ``shortest`` the shortest path alone. A query without a
    path within its limit has no row.
    """
    if method not in ("search", "pre", "shortest") or objective not in ("max", "min") or mode not in ("any", "both"):
        raise ValueError((method, objective, mode))

    def run(net: Network, q: int, src: int, dst: int, limit: int) -> list[tuple]:
        if method == "search":
            plan = search(net, src, dst, limit, objective, mode, dominance, path_mode)
        elif method == "pre":
            plan = best_by_enumeration(net, src, dst, limit, objective, mode)
        else:
            found = next(paths_within(net, src, dst, limit), None)
            plan = found and Plan(found[1], found[0], served(net.points(found[1]), mode), 1)
        return [(q, "-".join(map(str, plan.path)), plan.length, plan.value, len(plan.path), plan.labels)] if plan else []

    return _in_tiles(queries, edges, stops, omega, run, RESULT)


#: Planning queries of one slice of a tile.
QUERIES = 4_000


def _reaches(queries: DataFrame, edges: DataFrame, ends: DataFrame) -> DataFrame:
    """``queries`` with both ends' places and how far apart, in all, a stop on a path of theirs can be from both (see :func:`corridors`)."""
    least = edges.agg(F.min("length_m")).first()[0] or 1
    a, b = (ends.select(F.col("stop_id").alias(e), F.struct("x_m", "y_m").alias(f"{e}_at")) for e in ("src", "dst"))
    reach = F.ceil(F.col("max_len_m") * (1 + 0.5 / max(least, 1)) + 1).cast("bigint")
    return queries.select("query_id", "src", "dst", "max_len_m").join(a, "src").join(b, "dst").withColumn("reach", reach)


def _in_tiles(queries: DataFrame, edges: DataFrame, stops: DataFrame, omega: DataFrame | None, run: Callable[[Network, int, int, int, int], list[tuple]], schema: str) -> DataFrame:
    """``run(corridor, query_id, src, dst, max_len_m)`` for each query.

    A query lies in the tile of the middle between its ends, its corridor within half its reach around. Stops, with their edges and
    results as lists, are shuffled once for each tile whose border zone holds them, not once for each query.
    """
    ends = stops.groupBy("stop_id").agg(F.min("x_m").alias("x_m"), F.min("y_m").alias("y_m"))
    asked = _reaches(queries, edges, ends)
    asked = asked.withColumns({f"{v}_m": F.expr(f"(src_at.{v}_m + dst_at.{v}_m) div 2") for v in "xy"})
    asked = written(asked.select("query_id", "src", "dst", "max_len_m", "reach", "x_m", "y_m", *(F.col(f"{e}_at.{v}_m").alias(f"{e}_{v}") for e in ("src", "dst") for v in "xy")), "asked")
    points = tiles.dealt(asked, tiles.level_of(F.expr("reach div 2 + 2")), "query_id", QUERIES)
    out = edges.groupBy(F.col("src").alias("stop_id")).agg(*(F.collect_list(c).alias(c) for c in ("dst", "length_m")))
    full = ends.join(out, "stop_id", "left")
    if omega is not None:
        full = full.join(omega.groupBy("stop_id").agg(F.collect_list("transition_id").alias("won"), F.collect_list("mask").alias("mask")), "stop_id", "left")
    names, empty = [c.name for c in StructType.fromDDL(schema)], to_arrow_schema(StructType.fromDDL(schema))

    def lists(table: pa.Table, name: str) -> list:
        # Opened stop by stop, as queries reach them.
        return table[name].combine_chunks() if name in table.column_names else []

    def each(here: pa.Table, around: pa.Table) -> pa.Table:
        rows: list[tuple] = []
        if len(here) and len(around):
            ids, x, y = (around[c].to_numpy() for c in ("stop_id", "x_m", "y_m"))
            dst, length, won, mask = (lists(around, c) for c in ("dst", "length_m", "won", "mask"))
            steps: dict[int, list[tuple[int, int]]] = {}
            wins: dict[int, Points] = {}

            def step_of(i: int) -> list[tuple[int, int]]:
                if i not in steps:
                    steps[i] = sorted(zip(dst[i].as_py() or (), length[i].as_py() or (), strict=True))
                return steps[i]

            def wins_of(i: int) -> Points:
                if i not in wins:
                    pairs = zip(won[i].as_py() or (), mask[i].as_py() or (), strict=True) if len(won) else ()
                    wins[i] = Points((t, s) for t, m in pairs for s in (1, 2) if m & s)
                return wins[i]

            for q in here.select(["query_id", "src", "dst", "max_len_m", "reach", "src_x", "src_y", "dst_x", "dst_y"]).to_pylist():
                apart = sum(np.sqrt(((x - q[f"{e}_x"]) ** 2 + (y - q[f"{e}_y"]) ** 2).astype(np.float64)) for e in ("src", "dst"))
                at = np.flatnonzero(apart <= q["reach"]).tolist()
                inside = {int(ids[i]): i for i in at}
                net = Network()
                for v in sorted(inside):
                    net.near[v] = [(u, n) for u, n in step_of(inside[v]) if u in inside]
                    if got := wins_of(inside[v]):
                        net.won[v] = got
                rows += run(net, q["query_id"], q["src"], q["dst"], q["max_len_m"])
        return pa.table({n: pa.array([r[i] for r in rows], empty.field(n).type) for i, n in enumerate(names)})

    key = ["level", "tile", "slice"]
    placed = tiles.around_tiles(full, points.select(*key).distinct(), (*tiles.TILES, tiles.EVERYWHERE))
    return tiles.met(points, placed, each, schema)


def candidate_paths(queries: DataFrame, edges: DataFrame, stops: DataFrame, most: int = 1_000_000) -> DataFrame:
    """``(query_id, nth, length_m, path)``: every loopless path within the limit, shortest first; more than ``most`` of a query are an
    error, never cut."""

    def run(net: Network, q: int, src: int, dst: int, limit: int) -> list[tuple]:
        found = []
        for n, p, _ in all_paths(net, src, dst, limit):
            if len(found) >= most:
                raise ValueError(f"query {q} has more than {most} paths: search instead of enumerating")
            found.append((n, p))
        return [(q, i, n, p) for i, (n, p) in enumerate(sorted(found))]

    return _in_tiles(queries, edges, stops, None, run, "query_id bigint, nth bigint, length_m bigint, path array<bigint>")


def plan_by_queries(queries: DataFrame, edges: DataFrame, index: StopIndex, endpoints: EndpointIndex, k: int, objective: str = "max", mode: str = "any", method: str = "split") -> DataFrame:
    """The plain baseline: every candidate path is a reverse query of its own, all in one batch; then the best of each query.

    ``split`` asks a query's points one by one, so a stop that many candidates pass is asked once for all of them, and a candidate's
    result unites those of its stops in the task that lists it. The other methods ask whole candidates.
    """
    if method == "split":
        places = index.points().select("stop_id", "x_m", "y_m")
        passed = written(candidate_paths(queries, edges, places).select(F.explode("path").alias("stop_id")).distinct(), "passed")
        omega = written(vertex_omega(index, endpoints, (k,), passed, "queries").drop("k"), "omega-asked")
        return plan_routes(queries, edges, places, omega, objective, mode, "pre")
    stops = index.points().select("stop_id", "x_m", "y_m")
    # Written once, so the numbers of candidates are settled.
    paths = written(candidate_paths(queries, edges, stops).withColumn("cand", F.monotonically_increasing_id()), "candidates")
    points = paths.select("cand", F.posexplode("path").alias("q_idx", "stop_id")).join(stops, "stop_id")
    asked = points.select(F.col("cand").alias("query_id"), "q_idx", "x_m", "y_m", F.lit(None).cast("bigint").alias("exclude_route_id"))
    found = reverse_routes(index, endpoints, asked, k, mode, method=method).groupBy(F.col("query_id").alias("cand")).agg(F.count("*").alias("n_transitions"))
    return best_of(paths.join(found, "cand", "left").withColumn("n_transitions", F.coalesce("n_transitions", F.lit(0))), objective)


def best_of(candidates: DataFrame, objective: str = "max") -> DataFrame:
    """The best of ``candidates(query_id, path, length_m, n_transitions)`` of each query: by value, then length, then path."""
    value = -F.col("n_transitions") if objective == "max" else F.col("n_transitions")
    key = F.struct(value.alias("v"), "length_m", "path")
    best = candidates.groupBy("query_id").agg(F.min(key).alias("b"), F.count("*").alias("labels"))
    return best.select("query_id", F.array_join(F.col("b.path").cast("array<string>"), "-").alias("path"), "b.length_m", F.abs("b.v").alias("n_transitions"), F.size("b.path").cast("bigint").alias("n_stops"), "labels")
