"""Whether a box lies wholly nearer to a route than to a query: half-plane clipping of the box, in Arrow batches.

A box is inside a route's space if for no query point any of it is left after clipping it to the half-planes nearer to that point than
to each stop of the route. Clipping errs on one side: what is left by less than a hair counts as left, so a box is claimed only if surely
inside.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

#: In square metres, of a linear form of squared distances.
_HAIR = 1e-3


def _left_of(poly: np.ndarray, q: np.ndarray, r: np.ndarray) -> np.ndarray:
    """The part of a convex polygon not farther from q than from r."""
    a = 2.0 * (r - q)
    side = poly @ a - (r @ r - q @ q)  # at most 0 where q is as near
    keep = side <= _HAIR
    if keep.all():
        return poly
    if not keep.any():
        return poly[:0]
    out = []
    for i in range(len(poly)):
        j = (i + 1) % len(poly)
        if keep[i]:
            out.append(poly[i])
        if keep[i] != keep[j]:
            out.append(poly[i] + (poly[j] - poly[i]) * (side[i] / (side[i] - side[j])))
    return np.array(out)


def box_in_route_space(box: tuple[int, int, int, int], route: np.ndarray, query: np.ndarray) -> bool:
    x_lo, x_hi, y_lo, y_hi = box
    origin = np.array([x_lo, y_lo], float)  # near the origin floats lose least
    corners = np.array([[x_lo, y_lo], [x_hi, y_lo], [x_hi, y_hi], [x_lo, y_hi]], float) - origin
    stops = route - origin
    middle = corners.mean(axis=0)
    for q in query - origin:
        poly = corners
        for r in stops[np.argsort(((stops - middle) ** 2).sum(axis=1))]:
            poly = _left_of(poly, q, r)
            if not len(poly):
                break
        if len(poly):
            return False
    return True


def with_inside(pairs: DataFrame) -> DataFrame:
    """``pairs(probe_id, level, cell, box, n, maybe, route, q)`` with ``inside`` in place of the last three: whether the box is in the
    route's space. Only pairs that ``maybe`` are clipped."""

    def points(a: list[dict]) -> np.ndarray:
        return np.array([(p["x_m"], p["y_m"]) for p in a], float)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            inside = np.zeros(b.num_rows, bool)
            at = np.flatnonzero(np.array(b.column("maybe").to_pylist(), bool))
            for i, r in zip(at, b.take(pa.array(at)).select(["box", "route", "q"]).to_pylist(), strict=True):
                inside[i] = box_in_route_space(tuple(r["box"][c] for c in ("x_lo", "x_hi", "y_lo", "y_hi")), points(r["route"]), points(r["q"]))
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in ("probe_id", "level", "cell", "box", "n")), pa.array(inside)], names=["probe_id", "level", "cell", "box", "n", "inside"])

    out = "probe_id long, level int, cell long, box struct<x_lo: long, x_hi: long, y_lo: long, y_hi: long>, n int, inside boolean"
    return pairs.select("probe_id", "level", "cell", "box", "n", "maybe", "route", "q").mapInArrow(run, out)
