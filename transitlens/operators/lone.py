"""Filter, prune and verify of queries that are one point each, tile by tile inside tasks.

Many of them at once (each stop on a candidate path is one) meet the stops and endpoints around them in the task of their tile, so no pair
of query and stop, or of query and cell, is shuffled. What a query's stops leave is star-shaped around it: a place nearer to a stop than to
the query stays so farther out on the same ray. So if they rule out the border of a square around it, piece by piece, they rule out all
that lies beyond, and endpoints are looked at within the square only. Queries without such a square descend through the cells
(``pruning.py``).
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from ..functions import geometry as G
from ..plans.layout import EndpointIndex, StopIndex
from ..plans.shared import written
from . import tiles
from .filtering import with_stops

#: Tile level: its border zone is as wide as a cell of ``SEED_LEVEL``, whose cells lie whole in a tile, and wider than the widest square.
TILE, SEED_LEVEL = 15, 12
#: Half widths of the squares that are tried. The corners of the last are less than ``pruning.FAR_M`` away.
SQUARES = (1024, 1448, 2048, 2896)
#: Pieces of a side of a square; queries of one slice of a tile.
PIECES, QUERIES = 8, 4_000
_FOUND = "probe_id bigint, transition_id bigint, side string, x_m bigint, y_m bigint, dq bigint"


def are_lone(queries: DataFrame) -> bool:
    """Whether all of ``probes_of`` are queries of one point, with every route in the competition."""
    return queries.filter("size(all_q) <> 1 OR exclude_route_id IS NOT NULL").isEmpty()


def _placed(probes: DataFrame) -> DataFrame:
    at = probes.withColumns({c: F.col("q")[0][c] for c in ("x_m", "y_m")})
    return tiles.dealt(at, F.lit(TILE), "probe_id", QUERIES)


def _met(points: DataFrame, others: DataFrame, run: Callable[[pa.Table, pa.Table], pa.Table], schema: StructType) -> DataFrame:
    return tiles.met(points, tiles.around_tiles(others, points.select("level", "tile", "slice").distinct(), (TILE,)), run, schema)


def _int64(table: pa.Table, *names: str) -> list[np.ndarray]:
    return [table[c].to_numpy().astype(np.int64) for c in names]


def with_seeds(index: StopIndex, probes: DataFrame, seeds: int, sectors: int) -> DataFrame:
    """``probes`` with ``stops``, ids: of the stops in the cells around each, ``seeds`` dealt to the directions, nearest first.

    A stop serves all queries around it, so its routes are not repeated in each of them; :func:`opened` adds them.
    """
    schema = StructType(probes.schema.fields + StructType.fromDDL("stops array<bigint>").fields)
    names, share = probes.columns, max(1, seeds // sectors)

    def run(here: pa.Table, around: pa.Table) -> pa.Table:
        x, y = _int64(here, "x_m", "y_m")
        sx, sy, ids = _int64(around, "x_m", "y_m", "stop_id")
        gx, gy, sgx, sgy = (v + G._ORIGIN >> SEED_LEVEL for v in (x, y, sx, sy))
        rows, taken = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        by = np.lexsort((gy, gx))
        edges = np.flatnonzero(np.diff(gx[by], prepend=-1) | np.diff(gy[by], prepend=-1)) if len(by) else by
        for same in np.split(by, edges[1:]):
            if not len(same):
                continue
            near = np.flatnonzero((abs(sgx - gx[same[0]]) <= 1) & (abs(sgy - gy[same[0]]) <= 1))
            dx, dy = sx[near][None, :] - x[same][:, None], sy[near][None, :] - y[same][:, None]
            d2 = dx * dx + dy * dy
            i, j = np.nonzero(d2)
            sector = np.floor((np.arctan2(dy[i, j].astype(float), dx[i, j].astype(float)) + 3.14159265358979) / 6.2831853071796 * sectors).astype(np.int64)
            order = np.lexsort((ids[near[j]], d2[i, j], sector, i))
            group = i[order] * (sectors + 1) + sector[order]
            start = np.searchsorted(group, group)
            fine = order[np.arange(len(order)) - start < share]
            rows.append(same[i[fine]])
            taken.append(near[j[fine]])
        row, at = np.concatenate(rows), np.concatenate(taken)
        order = np.argsort(row, kind="stable")
        offsets = pa.array(np.searchsorted(row[order], np.arange(len(here) + 1)), pa.int32())
        return here.select(names).append_column("stops", pa.ListArray.from_arrays(offsets, pa.array(ids[at[order]])))

    return _met(_placed(probes), index.points().filter("size(routes) > 0").select("stop_id", "x_m", "y_m"), run, schema)


def by_ids(probes: DataFrame) -> bool:
    """Whether the probes are those of :func:`with_seeds`."""
    return dict(probes.dtypes)["stops"] == "array<bigint>"


def opened(index: StopIndex, probes: DataFrame) -> DataFrame:
    """Probes of :func:`with_seeds` as ``filtering.with_stops`` gives them."""
    stops = probes.select("probe_id", F.explode("stops").alias("stop_id")).join(index.points().select("stop_id", "x_m", "y_m", "routes"), "stop_id")
    return with_stops(probes.drop("stops"), stops)


def _borders() -> list[np.ndarray]:
    """``x_lo, x_hi, y_lo, y_hi`` of the pieces of each square's border, around the origin."""
    out = []
    for r in SQUARES:
        pieces = []
        ends = np.linspace(-r, r, PIECES + 1).astype(np.int64)
        for lo, hi in zip(ends[:-1], ends[1:], strict=True):
            pieces += [(lo, hi, -r, -r), (lo, hi, r, r), (-r, -r, lo, hi), (r, r, lo, hi)]
        out.append(np.array(pieces, np.int64).T)
    return out


class Seeds:
    """The stops that one query prunes with, placed around it."""

    def __init__(self, x: np.ndarray, y: np.ndarray, size: np.ndarray, routes: Callable[[], list[np.ndarray]], need: int):
        self.x, self.y, self.size, self.routes, self.need = x, y, size, routes, need
        self.half = x * x + y * y
        self.enough = size >= need
        self.through: np.ndarray | None = None

    def rule_out(self, x_lo: np.ndarray, x_hi: np.ndarray, y_lo: np.ndarray, y_hi: np.ndarray) -> np.ndarray:
        """Which boxes lie in the filter spaces of stops of enough distinct routes."""
        x, y = self.x[None, :], self.y[None, :]
        least = np.minimum(x * x_lo[:, None], x * x_hi[:, None]) + np.minimum(y * y_lo[:, None], y * y_hi[:, None])
        holding = 2 * least > self.half[None, :]
        out = holding[:, self.enough].any(axis=1)
        left = np.flatnonzero(~out)
        left = left[holding[left] @ self.size >= self.need]
        if len(left):
            if self.through is None:
                codes, code = np.unique(np.concatenate(self.routes()), return_inverse=True)
                self.through = np.zeros((len(self.size), len(codes)), np.float32)
                self.through[np.repeat(np.arange(len(self.size)), self.size), code] = 1
            out[left] = (holding[left].astype(np.float32) @ self.through > 0).sum(axis=1) >= self.need
        return out


def prune_by_tiles(index: EndpointIndex, stops: StopIndex, probes: DataFrame, need: int) -> tuple[DataFrame, DataFrame]:
    """Endpoints that the stops of each of ``probes`` leave, as ``prune_endpoints`` gives them, and those of the probes for which
    no square is closed: these find theirs by the descent."""
    empty, squares = to_arrow_schema(StructType.fromDDL(_FOUND)), _borders()

    def run(here: pa.Table, around: pa.Table) -> pa.Table:
        x, y, probe = _int64(here, "x_m", "y_m", "probe_id")
        is_stop = around["stop_id"].is_valid().combine_chunks()
        held, around = around.filter(is_stop), around.filter(pc.invert(is_stop)).sort_by("x_m")
        ex, ey = _int64(around, "x_m", "y_m")
        sx, sy, ids = _int64(held, "x_m", "y_m", "stop_id")
        lists = held["routes"].combine_chunks()
        n = lists.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
        route_at, routes = np.concatenate([[0], np.cumsum(n)]), lists.flatten().to_numpy()
        seeds = here["stops"].combine_chunks()
        at = np.concatenate([[0], np.cumsum(seeds.value_lengths().to_numpy(zero_copy_only=False))])
        by = np.argsort(ids)
        stop = by[np.searchsorted(ids[by], seeds.flatten().to_numpy())]
        far, rows, taken, dq = [], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for i in range(len(x)):
            s = stop[at[i] : at[i + 1]]
            own = Seeds(sx[s] - x[i], sy[s] - y[i], n[s], lambda s=s: [routes[route_at[j] : route_at[j + 1]] for j in s], need)
            r = next((r for r, border in zip(SQUARES, squares, strict=True) if own.rule_out(*border).all()), None)
            if r is None:
                far.append(i)
                continue
            lo, hi = np.searchsorted(ex, x[i] - r), np.searchsorted(ex, x[i] + r, side="right")
            e = lo + np.flatnonzero(abs(ey[lo:hi] - y[i]) <= r)
            dx, dy = ex[e] - x[i], ey[e] - y[i]
            left = np.flatnonzero(~own.rule_out(dx, dx, dy, dy))
            rows.append(np.full(len(left), probe[i]))
            taken.append(e[left])
            dq.append((dx * dx + dy * dy)[left])
        found = around.select(["transition_id", "side", "x_m", "y_m"]).take(pa.array(np.concatenate(taken)))
        found = found.add_column(0, "probe_id", pa.array(np.concatenate(rows))).append_column("dq", pa.array(np.concatenate(dq))).cast(empty)
        # A row without an endpoint names a query that goes on by the descent.
        open_ones = {c.name: pa.nulls(len(far), c.type) for c in empty} | {"probe_id": pa.array(probe[far])}
        return pa.concat_tables([found, pa.table(open_ones, schema=empty)])

    points = _placed(probes.select("probe_id", "q", "stops")).drop("q")
    both = index.points.select("transition_id", "side", "x_m", "y_m").unionByName(stops.points().select("stop_id", "x_m", "y_m", "routes"), allowMissingColumns=True)
    found = written(_met(points, both, run, StructType.fromDDL(_FOUND)), "near-candidates")
    left = found.filter("transition_id IS NULL").select("probe_id")
    return found.filter("transition_id IS NOT NULL"), probes.join(left, "probe_id", "left_semi")


#: Squared distances to the query below which a candidate's stops all lie in its tile's border zone.
NEAR_SQ = tiles.border(TILE) ** 2


def nearer_by_tiles(candidates: DataFrame, index: StopIndex) -> DataFrame:
    """``nearer_counts`` of distinct candidates with ``dq`` below ``NEAR_SQ``: the stops within that distance are measured."""
    schema = StructType.fromDDL("probe_id bigint, transition_id bigint, side string, nearer bigint")

    def run(here: pa.Table, around: pa.Table) -> pa.Table:
        x, y, dq = _int64(here, "x_m", "y_m", "dq")
        stops, n = tiles.Stops(around), np.zeros(len(here), np.int64)

        def solve(rows: np.ndarray, near: np.ndarray, d2: np.ndarray, box: tuple[int, int, int], zone: int) -> np.ndarray:
            fine = dq[rows] <= tiles.safe_sq(x[rows], y[rows], box, zone)
            i, j = np.nonzero((d2 < dq[rows][:, None]) & fine[:, None])
            at, code = stops.spread(near[j])
            many = max(1, len(stops.routes))
            met = np.unique(rows[i][at] * many + code)
            n[:] += np.bincount(met // many, minlength=len(n))
            return rows[~fine]

        if len(here):
            tiles.quarters(x, y, stops, tiles.box_of(here["tile"][0].as_py(), TILE), tiles.border(TILE), solve)
        return here.select(["probe_id", "transition_id", "side"]).append_column("nearer", pa.array(n))

    return _met(tiles.dealt(candidates, F.lit(TILE)), index.points().select("x_m", "y_m", "routes"), run, schema)
