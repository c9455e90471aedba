"""Forward queries: the routes nearest to a point and to a transition, exhaustive or by rings of cells.

By rings, an endpoint looks at the stops of its tile and of a border zone around it, in wider tiles until it has found enough routes within
that zone; what lies farther cannot be nearer. Distances are measured inside tasks (``tiles.py``), so no pair of endpoint and stop, or of
endpoint and route, is shuffled: what is written and shuffled grows with the endpoints and the stops.

A route ranks among an endpoint's k nearest if fewer than k routes are strictly nearer: routes as far as the k-th tie. That route, or stop,
then has the endpoint in its reverse result; so one forward pass answers the reverse queries of all routes, or of all stops.

Defined cases: no endpoints or no routes give no rows; with fewer than k routes all rank; a repeated endpoint or stop counts once
(:func:`kth_distances`) or once for each row (:func:`route_distances`).
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import ArrayType, IntegerType, LongType, StructField, StructType

from ..functions import geometry as G
from ..plans.layout import StopIndex, stop_routes
from ..plans.shared import written
from . import tiles
from .packed import pack, unpack

#: Stops up to which the exhaustive methods broadcast and pair them with every endpoint.
SCAN_STOPS = 100_000


def route_distances(endpoints: DataFrame, route_points: DataFrame) -> DataFrame:
    """``(transition_id, side, route_id, d2)`` for every endpoint and route: the exhaustive baseline, endpoints times stops.

    The stops are broadcast, at most ``SCAN_STOPS``; a stop's routes fan out only after the product.
    """
    stops = stop_routes(route_points).select(F.col("x_m").alias("sx"), F.col("y_m").alias("sy"), "routes")
    if stops.count() > SCAN_STOPS:
        raise ValueError(f"more than {SCAN_STOPS} stops: use nearest_by_rings")
    near = endpoints.select("transition_id", "side", "x_m", "y_m").crossJoin(F.broadcast(stops))
    near = near.select("transition_id", "side", G.sq_dist(F.col("x_m"), F.col("y_m"), F.col("sx"), F.col("sy")).alias("d2"), F.explode("routes").alias("route_id"))
    return near.groupBy("transition_id", "side", "route_id").agg(F.min("d2").alias("d2"))


def nearest_routes(endpoints: DataFrame, route_points: DataFrame, k: int, ties: str = "rank") -> DataFrame:
    """The k nearest routes of each endpoint; ``rank`` keeps ties of the k-th, ``row`` breaks them by route id."""
    order = Window.partitionBy("transition_id", "side").orderBy("d2", *(["route_id"] if ties == "row" else []))
    rank = F.row_number() if ties == "row" else F.rank()
    return route_distances(endpoints, route_points).withColumn("rank", rank.over(order)).filter(F.col("rank") <= k)


def kth_distances(endpoints: DataFrame, index: StopIndex, ks: tuple[int, ...]) -> DataFrame:
    """``(transition_id, side, x_m, y_m, kth)`` of distinct endpoints: for each of ``ks`` the squared distance of the k-th nearest route
    (the farthest, with fewer routes). Written."""
    keys = ["transition_id", "side", "x_m", "y_m"]
    left = endpoints.select(*keys).filter("x_m IS NOT NULL AND y_m IS NOT NULL")
    n_routes = index.points().select(F.explode("routes")).distinct().count()
    if not n_routes:
        return written(left.distinct().limit(0).withColumn("kth", F.array().cast("array<bigint>")), "kth")
    wanted = tuple(min(k, n_routes) for k in ks)
    need = max(wanted)
    # A stop with so many routes settles every k by itself, so more of them need not travel.
    stops = index.points().select("x_m", "y_m", F.slice("routes", 1, need).alias("routes"))
    parts = []
    for level in (*tiles.TILES, tiles.EVERYWHERE):
        found = written(_kth_by_tiles(left, stops, level, wanted), "kth")
        parts.append(found.filter("kth IS NOT NULL"))
        left = found.filter("kth IS NULL").drop("kth")
        if left.isEmpty():
            break
    return reduce(DataFrame.unionByName, parts)


def _tiled(points: DataFrame, stops: DataFrame, run: Callable[[pa.Table, tiles.Stops, tuple[int, int, int], int], pa.Table], schema: str, levels: tuple[int, ...]) -> DataFrame:
    """``run(points, stops, box, border)`` for each tile and slice of ``points(..., level, tile, slice)``, of ``levels`` only."""
    key = ["level", "tile", "slice"]
    placed = tiles.around_tiles(stops, points.select(*key).distinct(), levels)

    empty = to_arrow_schema(StructType.fromDDL(schema)).empty_table()

    def each(here: pa.Table, around: pa.Table) -> pa.Table:
        if not len(here):
            return empty
        level, tile = here["level"][0].as_py(), here["tile"][0].as_py()
        return run(here, tiles.Stops(around), tiles.box_of(tile, level), tiles.border(level))

    return points.groupBy(*key).cogroup(placed.groupBy(*(f"_{c}" for c in key))).applyInArrow(each, schema)


def _kth_by_tiles(points: DataFrame, stops: DataFrame, level: int, ks: tuple[int, ...]) -> DataFrame:
    """Distinct ``points`` with ``kth``, null where the border zone is too narrow to tell."""
    keys = ["transition_id", "side", "x_m", "y_m"]

    def run(here: pa.Table, stops: tiles.Stops, box: tuple[int, int, int], zone: int) -> pa.Table:
        here = here.select(keys).group_by(keys).aggregate([])
        x, y = (here[c].to_numpy().astype(np.int64) for c in ("x_m", "y_m"))
        kth = np.full((len(x), len(ks)), -1, np.int64)

        def solve(rows: np.ndarray, near: np.ndarray, d2: np.ndarray, box: tuple[int, int, int], zone: int) -> np.ndarray:
            got = tiles.kth_of(d2, near, stops, ks)
            fine = (got[:, -1] >= 0) & (got.max(axis=1) < tiles.safe_sq(x[rows], y[rows], box, zone)) & (got.min(axis=1) >= 0)
            kth[rows[fine]] = got[fine]
            return rows[~fine]

        tiles.quarters(x, y, stops, box, zone, solve)
        known = kth[:, -1] >= 0
        offsets = pa.array(np.arange(len(x) + 1) * len(ks), pa.int32())
        lists = pa.ListArray.from_arrays(offsets, pa.array(kth.ravel()))
        return here.append_column("kth", pc.if_else(pa.array(known), lists, pa.scalar(None, lists.type)))

    return _tiled(tiles.dealt(points, F.lit(level)), stops, run, "transition_id bigint, side string, x_m bigint, y_m bigint, kth array<bigint>", (level,))


def _within(points: DataFrame, index: StopIndex, run: Callable, schema: str, columns: list[str]) -> DataFrame:
    """``run(points, stops, pairs)`` for the ``points(..., kth)`` of each tile, with every stop no farther than the last of ``kth``:
    ``pairs`` are positions of points and of stops, and squared distances."""
    radius = F.ceil(F.sqrt(F.element_at("kth", -1).cast("double"))) + 1
    level = tiles.level_of(radius)

    def each(here: pa.Table, stops: tiles.Stops, box: tuple[int, int, int], zone: int) -> pa.Table:
        x, y = (here[c].to_numpy().astype(np.int64) for c in ("x_m", "y_m"))
        lists = here["kth"].combine_chunks()
        last = lists.flatten().to_numpy()[np.cumsum(lists.value_lengths().to_numpy(zero_copy_only=False)) - 1]
        found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

        def solve(rows: np.ndarray, near: np.ndarray, d2: np.ndarray, box: tuple[int, int, int], zone: int) -> np.ndarray:
            fine = last[rows] < tiles.safe_sq(x[rows], y[rows], box, zone)
            i, j = np.nonzero((d2 <= last[rows][:, None]) & fine[:, None])
            found.append((rows[i], near[j], d2[i, j]))
            return rows[~fine]

        tiles.quarters(x, y, stops, box, zone, solve)
        point, stop, d2 = (np.concatenate([f[n] for f in found] or [np.zeros(0, np.int64)]) for n in range(3))
        return run(here, stops, point, stop, d2)

    return _tiled(tiles.dealt(points, level), index.points().select("x_m", "y_m", *columns), each, schema, (*tiles.TILES, tiles.EVERYWHERE))


def _listed(here: pa.Table, stops: tiles.Stops, point: np.ndarray, stop: np.ndarray, d2: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For pairs of a point and a stop, where each point's list starts, and the lists end to end: routes and their squared distances,
    nearest first."""
    at, code = stops.spread(stop)
    point, d2 = point[at], d2[at]
    by = np.lexsort((d2, code, point))
    point, code, d2 = point[by], code[by], d2[by]
    first = np.ones(len(point), bool)
    first[1:] = (point[1:] != point[:-1]) | (code[1:] != code[:-1])
    point, code, d2 = point[first], code[first], d2[first]
    by = np.lexsort((code, d2, point))
    return np.searchsorted(point, np.arange(len(here) + 1)), stops.routes[code[by]], d2[by]


def lists_within(points: DataFrame, index: StopIndex, more: tuple[str, ...] = ()) -> DataFrame:
    """``(transition_id, side, routes, d2)`` and the whole numbers ``more`` of distinct ``points(transition_id, side, x_m, y_m, kth)``: the routes no farther than the last
    of ``kth`` and their squared distances, nearest first."""

    def run(here: pa.Table, *found) -> pa.Table:
        offsets, routes, d2 = _listed(here, *found)
        lists = [pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(v)) for v in (routes, d2)]
        return pa.table({"transition_id": here["transition_id"], "side": here["side"], "routes": lists[0], "d2": lists[1], **{c: here[c] for c in more}})

    schema = "transition_id bigint, side string, routes array<bigint>, d2 array<bigint>" + "".join(f", {c} bigint" for c in more)
    return _within(points, index, run, schema, ["routes"])


#: A list of routes as bytes, and how many of them count for each k (``packed.py``).
_PACKED = "transition_id bigint, side string, packed binary, n array<int>"


def _packed_within(points: DataFrame, index: StopIndex, ks: tuple[int, ...]) -> DataFrame:
    """:func:`lists_within`, packed where they are found."""

    def run(here: pa.Table, *found) -> pa.Table:
        offsets, routes, d2 = _listed(here, *found)
        packed, n = pack(np.diff(offsets), routes, d2, ks)
        return pa.table({"transition_id": here["transition_id"], "side": here["side"], "packed": packed, "n": n})

    return _within(points, index, run, _PACKED, ["routes"])


def _packed_lists(lists: DataFrame, ks: tuple[int, ...]) -> DataFrame:
    """``lists(transition_id, side, routes, d2)`` packed."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            routes, d2 = (b.column(c) for c in ("routes", "d2"))
            packed, n = pack(routes.value_lengths().to_numpy(zero_copy_only=False), routes.flatten().to_numpy(), d2.flatten().to_numpy(), ks)
            yield pa.RecordBatch.from_arrays([b.column("transition_id"), b.column("side"), packed, n], names=["transition_id", "side", "packed", "n"])

    return lists.select("transition_id", "side", "routes", "d2").mapInArrow(run, _PACKED)


def ends_again(points: DataFrame) -> DataFrame | None:
    """``(transition_id, side)`` of ends that distinct ``points`` have at several places, written; None without any."""
    again = points.groupBy("transition_id", "side").agg(F.count("*").alias("n")).filter("n > 1").drop("n")
    return None if again.isEmpty() else written(again, "ends-again")


def _ranked(endpoints: DataFrame, index: StopIndex, k: int) -> tuple[DataFrame, DataFrame | None]:
    """``kth`` of the ends that lie at one place each, and the finished lists of those at several (None without any)."""
    kth = kth_distances(endpoints, index, (k,))
    again = ends_again(kth)
    if again is None:
        return kth, None
    # Ends at several places: a route counts from the nearest of them, and they are ranked together.
    each = lists_within(kth.join(again, ["transition_id", "side"], "left_semi"), index).select("transition_id", "side", F.explode(F.arrays_zip("routes", "d2")).alias("p"))
    each = each.groupBy("transition_id", "side", F.col("p.routes").alias("route_id")).agg(F.min("p.d2").alias("d2"))
    each = each.withColumn("rank", F.rank().over(Window.partitionBy("transition_id", "side").orderBy("d2"))).filter(F.col("rank") <= k)
    each = each.groupBy("transition_id", "side").agg(F.array_sort(F.collect_list(F.struct("d2", "route_id"))).alias("p"))
    return kth.join(again, ["transition_id", "side"], "left_anti"), each.select("transition_id", "side", F.col("p.route_id").alias("routes"), F.col("p.d2").alias("d2"))


def ranked_lists(endpoints: DataFrame, index: StopIndex, k: int) -> DataFrame:
    """``(transition_id, side, routes, d2)``: a row per end of a transition with the routes that rank among its k nearest, ties kept, and
    their squared distances, nearest first."""
    kth, each = _ranked(endpoints, index, k)
    lists = lists_within(kth, index)
    return lists if each is None else lists.unionByName(each)


def nearest_by_rings(endpoints: DataFrame, index: StopIndex, k: int) -> DataFrame:
    """``(transition_id, side, route_id, d2)``: the routes that rank among the k nearest of each endpoint, ties kept."""
    zipped = F.explode(F.arrays_zip("routes", "d2")).alias("p")
    return ranked_lists(endpoints, index, k).select("transition_id", "side", zipped).select("transition_id", "side", F.col("p.routes").alias("route_id"), "p.d2")


def stops_by_rings(endpoints: DataFrame, index: StopIndex, ks: tuple[int, ...]) -> DataFrame:
    """``(k, stop_id, transition_id, side)``: stops than which fewer than k routes are strictly nearer to the endpoint."""
    ks = tuple(sorted(ks))

    def run(here: pa.Table, stops: tiles.Stops, point: np.ndarray, stop: np.ndarray, d2: np.ndarray) -> pa.Table:
        lists = here["kth"].combine_chunks().flatten().to_numpy().reshape(len(here), len(ks))
        which, at = np.nonzero((d2[None, :] <= lists.T[:, point]))
        taken = pa.array(point[at])
        return pa.table({"k": pa.array(np.array(ks, np.int32)[which]), "stop_id": pa.array(stops.id[stop[at]]), "transition_id": here["transition_id"].take(taken), "side": here["side"].take(taken)})

    return _within(kth_distances(endpoints, index, ks), index, run, "k int, stop_id bigint, transition_id bigint, side string", ["stop_id"])


def _packed_sides(endpoints: DataFrame, index: StopIndex, ks: tuple[int, ...]) -> DataFrame:
    """:func:`sides_by_rings` with ``o`` and ``d`` packed."""
    kth, each = _ranked(endpoints, index, max(ks))
    lists = _packed_within(kth, index, ks)
    lists = lists if each is None else lists.unionByName(_packed_lists(each, ks))
    of = [F.collect_list(F.when(F.col("side") == s, F.struct("packed", "n"))).alias(s) for s in "od"]
    return lists.repartition("transition_id").groupBy("transition_id").agg(*of)


def _opened(rows: DataFrame) -> DataFrame:
    """Rows of :func:`_packed_sides`, other columns too, with the routes in ``o`` and ``d`` and their numbers in ``n_o`` and ``n_d``."""
    names = rows.columns
    fields = [StructField(f.name, ArrayType(LongType()) if f.name in ("o", "d") else f.dataType) for f in rows.schema]
    numbers = [StructField(f"n_{c}", ArrayType(IntegerType())) for c in "od"]

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            column = dict(zip(names, b.columns, strict=True))
            for c in "od":
                per = np.concatenate([[0], np.cumsum(column[c].value_lengths().to_numpy(zero_copy_only=False))])
                packed, n = column[c].flatten().flatten()
                size, ids = unpack(packed, n)
                for name, ends, flat in ((c, size, ids), (f"n_{c}", n.value_lengths().to_numpy(zero_copy_only=False), n.flatten())):
                    offsets = np.concatenate([[0], np.cumsum(ends)])[per]
                    column[name] = pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(flat))
            yield pa.RecordBatch.from_arrays(list(column.values()), names=list(column))

    return rows.mapInArrow(run, StructType([*fields, *numbers]))


def sides_by_rings(endpoints: DataFrame, index: StopIndex, ks: tuple[int, ...]) -> DataFrame:
    """``(transition_id, o, d, n_o, n_d)``: a row per transition with the routes that rank among the nearest of each end, those that count
    for a smaller k first, and how many of them do for each of ``ks``; empty lists for an end without any. Lists are shuffled as bytes."""
    return _opened(_packed_sides(endpoints, index, ks))


def ends(nth: int) -> tuple[Column, Column]:
    """Of a row of :func:`sides_by_rings`, the routes of both ends for the ``nth`` of its ``ks``."""
    return tuple(F.slice(c, 1, F.coalesce(F.get(f"n_{c}", F.lit(nth)), F.lit(0))) for c in "od")


def _masked(nth: int, mode: str) -> Column:
    o, d = ends(nth)
    groups = [(F.array_intersect(o, d), 3)]
    if mode == "any":
        groups += [(F.array_except(o, d), 1), (F.array_except(d, o), 2)]
    return F.concat(*(F.transform(routes, lambda r: F.struct(r.alias("route_id"), F.lit(mask).alias("mask"))) for routes, mask in groups))  # noqa: B023


def masks_by_rings(endpoints: DataFrame, index: StopIndex, ks: tuple[int, ...], mode: str = "any", keep: Callable[[DataFrame], DataFrame] = lambda x: x) -> DataFrame:
    """``(k, transition_id, route_id, mask)``: for each k the routes that rank among the k nearest of one end (``any``) or of both.

    ``keep`` may add columns to the rows of transitions before their lists are opened; they follow.
    """
    if mode not in ("any", "both"):
        raise ValueError(f"mode {mode!r}")
    rows = _opened(keep(_packed_sides(endpoints, index, ks)))
    more = [c for c in rows.columns if c not in ("transition_id", "o", "d", "n_o", "n_d")]
    each = F.explode(F.array(*(F.struct(F.lit(k).alias("k"), _masked(i, mode).alias("found")) for i, k in enumerate(ks)))).alias("e")
    return rows.select("transition_id", *more, each).select("e.k", "transition_id", *more, F.explode("e.found").alias("p")).select("k", "transition_id", "p.*", *more)


def transition_routes(found: DataFrame, mode: str = "any") -> DataFrame:
    """``(transition_id, route_id, mask)`` of ``found(transition_id, side, route_id)``: routes among the k nearest of one endpoint
    (``any``) or of both."""
    if mode not in ("any", "both"):
        raise ValueError(f"mode {mode!r}")
    marked = found.withColumn("mask", F.when(F.col("side") == "o", 1).otherwise(2))
    both = marked.groupBy("transition_id", "route_id").agg(F.bit_or("mask").alias("mask"))
    return both if mode == "any" else both.filter("mask = 3")
