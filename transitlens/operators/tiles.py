"""Distances from points to the stops around them, tile by tile inside tasks.

Endpoints go to the tile they lie in, stops to every tile whose border zone they lie in; a task measures a tile's points against its
stops with numpy and hands on what was asked for only. What is shuffled is each point once and each stop a little more than once, however
many stops, or routes through them, lie around a point. A tile of many points is dealt out in slices; inside a slice, points are split into
quarters while they are many.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ..functions import geometry as G
from ..plans.shared import few

#: Tile levels (width ``2**level`` m); the border zone is an eighth of a tile wide.
TILES = (15, 18, 21)
#: A level above all others, whose one tile holds all points and meets every stop: coordinates stay below half its width.
EVERYWHERE = 31
#: Points of one slice, distances measured and routes listed at once, rows of the table of slices that is broadcast.
SLICE, BLOCK, LISTED, FEW_TILES = 50_000, 1 << 20, 1 << 20, 100_000


def border(level: int) -> int:
    return 1 << 30 if level == EVERYWHERE else 1 << level - 3


def level_of(radius: Column) -> Column:
    """The finest tile level whose border zone holds the radius."""
    found = F.lit(EVERYWHERE)
    for s in reversed(TILES):
        found = F.when(radius <= border(s), F.lit(s)).otherwise(found)
    return found


def dealt(points: DataFrame, level: Column, key: str = "transition_id", most: int = SLICE) -> DataFrame:
    """``points`` with ``level``, ``tile`` and ``slice``: about ``most`` of a tile are in one slice, by ``key``."""
    rows = points.withColumn("level", level)
    rows = rows.withColumn("tile", G.grid_cell(G.grid(F.col("x_m"), F.col("level")), G.grid(F.col("y_m"), F.col("level"))))
    counts = rows.groupBy("level", "tile").agg(F.ceil(F.count("*") / most).cast("int").alias("n_slices")).filter("n_slices > 1")
    rows = rows.join(few(counts, FEW_TILES), ["level", "tile"], "left")
    return rows.withColumn("slice", F.coalesce(F.pmod(F.xxhash64(key), F.col("n_slices")).cast("int"), F.lit(0))).drop("n_slices")


def around_tiles(stops: DataFrame, tiles: DataFrame, levels: tuple[int, ...]) -> DataFrame:
    """``stops`` once for each of ``tiles(level, tile, slice)`` whose border zone holds them, with its key as ``_level, _tile, _slice``."""
    x, y = F.col("x_m"), F.col("y_m")
    at = []
    for s in levels:
        b = border(s)
        gx, gy = (F.sequence(G.grid(v - b, s), G.grid(v + b, s)) for v in (x, y))
        at.append(F.flatten(F.transform(gx, lambda i: F.transform(gy, lambda j: F.struct(F.lit(s).alias("level"), G.grid_cell(i, j).alias("tile"))))))  # noqa: B023
    placed = stops.withColumn("_at", F.explode(F.concat(*at))).select("*", F.col("_at.level").alias("_level"), F.col("_at.tile").alias("_tile")).drop("_at")
    return placed.join(few(tiles.toDF("_level", "_tile", "_slice"), FEW_TILES), ["_level", "_tile"])


def met(points: DataFrame, placed: DataFrame, run: Callable[[pa.Table, pa.Table], pa.Table], schema: StructType | str) -> DataFrame:
    """``run(points, around)`` for each tile and slice, of ``points(..., level, tile, slice)`` and of what :func:`around_tiles` gave.

    Rows are few for the work they make, so they are dealt out to a number of tasks that does not follow from their size.
    """
    spark, here = points.sparkSession, ("level", "tile", "slice")
    there = [f"_{c}" for c in here]
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 4 * spark.sparkContext.defaultParallelism)
    return points.repartition(tasks, *here).groupBy(*here).cogroup(placed.repartition(tasks, *there).groupBy(*there)).applyInArrow(run, schema)


class Stops:
    """A tile's stops, in numpy."""

    def __init__(self, table: pa.Table):
        self.x, self.y = (table.column(c).to_numpy().astype(np.int64) for c in ("x_m", "y_m"))
        self.id = table.column("stop_id").to_numpy() if "stop_id" in table.column_names else None
        self.offsets, self.routes, self.code = np.zeros(len(self.x) + 1, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
        if "routes" in table.column_names:
            routes = table.column("routes").combine_chunks()
            lengths = routes.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
            self.offsets = np.concatenate([[0], np.cumsum(lengths)])
            self.routes, self.code = np.unique(routes.flatten().to_numpy(), return_inverse=True)

    def spread(self, stop: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For each of ``stop`` its routes: positions in ``stop``, and route codes."""
        n = self.offsets[stop + 1] - self.offsets[stop]
        row = np.repeat(np.arange(len(stop)), n)
        return row, self.code[self.offsets[stop][row] + np.arange(len(row)) - np.repeat(np.cumsum(n) - n, n)]


def _blocks(x: np.ndarray, y: np.ndarray, stops: Stops, rows: np.ndarray, near: np.ndarray, box: tuple[int, int, int], zone: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, tuple, int]]:
    """Points ``rows`` against stops ``near`` in blocks of bounded size: ``(rows, near, squared distances)``."""
    step = max(1, BLOCK // max(1, len(near)))
    for lo in range(0, len(rows), step):
        part = rows[lo : lo + step]
        dx, dy = x[part][:, None] - stops.x[near][None, :], y[part][:, None] - stops.y[near][None, :]
        yield part, near, dx * dx + dy * dy, box, zone


def quarters(x: np.ndarray, y: np.ndarray, stops: Stops, box: tuple[int, int, int], zone: int, solve: Callable) -> None:
    """Runs ``solve(rows, near, d2, box, zone)``, which returns the rows it could not settle, on ever smaller boxes first: a
    quarter's border zone is narrower, and what it leaves goes back to the whole box."""

    def run(rows: np.ndarray, near: np.ndarray, box: tuple[int, int, int], zone: int) -> np.ndarray:
        x0, y0, width = box
        if len(rows) * len(near) > BLOCK and width > 64:
            half, left = width // 2, []
            for qx, qy in ((x0, y0), (x0 + half, y0), (x0, y0 + half), (x0 + half, y0 + half)):
                inner = rows[(x[rows] >= qx) & (x[rows] < qx + half) & (y[rows] >= qy) & (y[rows] < qy + half)]
                if len(inner):
                    z = max(1, zone // 2)
                    sx, sy = stops.x[near], stops.y[near]
                    left.append(run(inner, near[(sx >= qx - z) & (sx < qx + half + z) & (sy >= qy - z) & (sy < qy + half + z)], (qx, qy, half), z))
            rows = np.concatenate(left) if left else rows[:0]
        rest = [solve(*b) for b in _blocks(x, y, stops, rows, near, box, zone)]
        return np.concatenate(rest) if rest else rows[:0]

    run(np.arange(len(x)), np.arange(len(stops.x)), box, zone)


def box_of(tile: int, level: int) -> tuple[int, int, int]:
    gx, gy = tile >> 31, tile & (1 << 31) - 1
    return (gx << level) - G._ORIGIN, (gy << level) - G._ORIGIN, 1 << level


def safe_sq(x: np.ndarray, y: np.ndarray, box: tuple[int, int, int], zone: int) -> np.ndarray:
    """Squared distance that stops outside the box and its border zone reach at least."""
    x0, y0, width = box
    safe = np.minimum(np.minimum(x - x0, x0 + width - x), np.minimum(y - y0, y0 + width - y)) + zone
    return safe * safe


def kth_of(d2: np.ndarray, near: np.ndarray, stops: Stops, ks: tuple[int, ...]) -> np.ndarray:
    """For each row of ``d2`` the squared distance at which the k-th distinct route is met, for each of ``ks``; -1 with fewer routes."""
    out = np.full((len(d2), len(ks)), -1, np.int64)
    left, take = np.arange(len(d2)), 2
    many = max(1, len(stops.code) // max(1, len(stops.x)))
    while len(left) and len(near):
        take = min(take, len(near))
        step = max(1, LISTED // (take * many))
        rest = [_kth_among(d2, left[lo : lo + step], take, near, stops, ks, out) for lo in range(0, len(left), step)]
        left = np.concatenate(rest)
        if take == len(near):
            break
        take *= 4
    return out


def _kth_among(d2: np.ndarray, rows: np.ndarray, take: int, near: np.ndarray, stops: Stops, ks: tuple[int, ...], out: np.ndarray) -> np.ndarray:
    """:func:`kth_of` among the ``take`` nearest stops of ``rows``; returns the rows that need more."""
    dist = d2[rows]
    if take < len(near):
        part = np.argpartition(dist, take - 1, axis=1)[:, :take]
        dist = np.take_along_axis(dist, part, axis=1)
    else:
        part = np.broadcast_to(np.arange(len(near)), dist.shape)
    order = np.argsort(dist, axis=1, kind="stable")
    dist, part = np.take_along_axis(dist, order, axis=1), np.take_along_axis(part, order, axis=1)
    at, code = stops.spread(near[part].ravel())
    # The first position of each route of a row, then how many routes a row has met up to each position.
    row = at // take
    by = np.argsort(row * len(stops.routes) + code, kind="stable")
    key = row[by] * len(stops.routes) + code[by]
    first = np.ones(len(key), bool)
    first[1:] = key[1:] != key[:-1]
    met = np.bincount(at[by][first], minlength=len(rows) * take).reshape(len(rows), take).cumsum(axis=1)
    for i, k in enumerate(ks):
        has = met[:, -1] >= k
        out[rows[has], i] = dist[has, np.argmax(met[has] >= k, axis=1)]
    return rows[met[:, -1] < max(ks)]
