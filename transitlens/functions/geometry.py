"""Plane geometry as column expressions over integers: distances, half-planes, boxes, cells."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Cells are squares of ``2**shift`` metres; a level is its shift. Some serve the descent through an index, from a few cells of 262 km
#: down, all of them the search around a point.
DESCENT = (18, 14, 12, 10)
LEVELS = (10, 12, 14, 16, 18, 20)
_ORIGIN = 1 << 30


def sq_dist(x1: Column, y1: Column, x2: Column, y2: Column) -> Column:
    return (x1 - x2) * (x1 - x2) + (y1 - y2) * (y1 - y2)


def nearest_sq(x: Column, y: Column, points: Column) -> Column:
    """Squared distance to the nearest of an array of ``(x_m, y_m)``."""
    return F.array_min(F.transform(points, lambda q: sq_dist(x, y, q["x_m"], q["y_m"])))


def edge_length(x1: Column, y1: Column, x2: Column, y2: Column) -> Column:
    """Length in metres, rounded once, so that sums along a path are exact."""
    return F.round(F.sqrt(sq_dist(x1, y1, x2, y2).cast("double"))).cast("bigint")


def inside_bisector(box: Column, px: Column, py: Column, q: Column) -> Column:
    """Whether every point of the box is strictly nearer to p than to q.

    The difference of the squared distances is linear, so over a box it is largest at a corner that each axis picks for itself.
    """
    ax, ay = 2 * (q["x_m"] - px), 2 * (q["y_m"] - py)
    rest = px * px + py * py - q["x_m"] * q["x_m"] - q["y_m"] * q["y_m"]
    return F.greatest(ax * box["x_lo"], ax * box["x_hi"]) + F.greatest(ay * box["y_lo"], ay * box["y_hi"]) + rest < 0


def inside_filter_space(box: Column, px: Column, py: Column, query: Column) -> Column:
    """Whether every point of the box is strictly nearer to p than to any query point."""
    return F.forall(query, lambda q: inside_bisector(box, px, py, q))


def in_route_space(x: Column, y: Column, route: Column, query: Column) -> Column:
    """Whether a point is strictly nearer to a route (array of points) than to the query."""
    return nearest_sq(x, y, route) < nearest_sq(x, y, query)


def _gap(lo: Column, hi: Column, v: Column) -> Column:
    return F.greatest(lo - v, F.lit(0), v - hi)


def box_min_sq(box: Column, points: Column) -> Column:
    """Least squared distance between a box and an array of points."""
    return F.array_min(F.transform(points, lambda q: _gap(box["x_lo"], box["x_hi"], q["x_m"]) * _gap(box["x_lo"], box["x_hi"], q["x_m"]) + _gap(box["y_lo"], box["y_hi"], q["y_m"]) * _gap(box["y_lo"], box["y_hi"], q["y_m"])))


def point_box_min_sq(box: Column, x: Column, y: Column) -> Column:
    dx, dy = _gap(box["x_lo"], box["x_hi"], x), _gap(box["y_lo"], box["y_hi"], y)
    return dx * dx + dy * dy


def point_box_max_sq(box: Column, x: Column, y: Column) -> Column:
    dx, dy = F.greatest(F.abs(x - box["x_lo"]), F.abs(x - box["x_hi"])), F.greatest(F.abs(y - box["y_lo"]), F.abs(y - box["y_hi"]))
    return dx * dx + dy * dy


def boxes_max_sq(a: Column, b: Column) -> Column:
    """Greatest squared distance between a point of one box and a point of the other."""
    dx, dy = (F.greatest(F.abs(a[f"{v}_hi"] - b[f"{v}_lo"]), F.abs(b[f"{v}_hi"] - a[f"{v}_lo"])) for v in "xy")
    return dx * dx + dy * dy


def grid_cell(gx: Column, gy: Column) -> Column:
    """The cell of whole-number grid positions."""
    return F.shiftleft(gx, 31).bitwiseOR(gy)


def cell_at(x: Column, y: Column, level: int) -> Column:
    return grid_cell(grid(x, level), grid(y, level))


def parent_cell(cell: Column, up: int) -> Column:
    """The cell ``up`` levels of halving above."""
    return grid_cell(F.shiftright(cell, 31 + up), F.shiftright(cell.bitwiseAND((1 << 31) - 1), up))


def grid(v: Column, level: int | Column) -> Column:
    """A coordinate's position in a level's grid, from the plane's lower edge."""
    shifted = v.cast("bigint") + _ORIGIN
    if isinstance(level, int):
        return F.shiftright(shifted, level)
    return F.floor(shifted / F.pow(F.lit(2.0), level)).cast("bigint")


def project_lonlat(lon: Column, lat: Column, lat0: float) -> tuple[Column, Column]:
    """Equirectangular projection to whole metres at a reference latitude."""
    metres = 111_320.0
    return F.round(lon * F.cos(F.radians(F.lit(lat0))) * metres).cast("bigint"), F.round(lat * metres).cast("bigint")
