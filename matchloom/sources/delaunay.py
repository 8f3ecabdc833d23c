"""Delaunay edges by an interval test on each pair, without a geometry library.

The circles through two points a, b have their centres on the bisector of the pair; a third
point c allows only the centres on one side of where the circle goes through c as well. The
pair is an edge if the sides that all others allow have a centre in common. Positions are
compared as cross products of integers, exactly: position(c) = -(ca . cb) / cross(ab, ac).
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

NEAR = 24
PAIR_CELLS = 4


#: Points around a point that are tried first, and points of a grid cell.
AROUND = 48
CELL_POINTS = 8


def delaunay_edges(points: DataFrame) -> DataFrame:
    """``(u, v, w)`` of distinct integer points ``(id, x, y)``. Of four or more points on a
    circle all pairs count. The points go to every task once, 24 bytes each: each task tests the
    pairs of its own points among those around them, as far as they can matter.
    """
    table = points.select("id", "x", "y").orderBy("id").toArrow()
    n = len(table)
    ids = table.column("id").to_numpy()
    xy = np.stack([table.column("x").to_numpy(), table.column("y").to_numpy()], axis=1) if n else np.zeros((0, 2), np.int64)
    shared = points.sparkSession.sparkContext.broadcast((ids, xy))

    def run(batches):
        ids, xy = shared.value
        grid = Grid(xy)
        for batch in batches:
            for k in np.searchsorted(ids, batch.column(0).to_numpy()):
                others = partners(xy, grid, int(k))
                if len(others):
                    gap = ((xy[others] - xy[k]) ** 2).sum(axis=1)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(others), ids[k])), pa.array(ids[others]), pa.array(gap)], names=["u", "v", "w"])

    return points.select("id").repartition(max(1, min(64, n // 64))).mapInArrow(run, "u long, v long, w long")


class Grid:
    """Points by cells of a square grid, to find those around a place."""

    def __init__(self, xy: np.ndarray):
        self.xy = xy
        self.low = xy.min(axis=0) if len(xy) else np.zeros(2, np.int64)
        span = (xy.max(axis=0) - self.low + 1) if len(xy) else np.ones(2, np.int64)
        self.side = max(1, int(np.sqrt(float(span[0]) * float(span[1]) * CELL_POINTS / max(len(xy), 1))), int(span.max()) >> 12)
        self.cells = span // self.side + 1
        place = (xy - self.low) // self.side
        name = place[:, 0] * self.cells[1] + place[:, 1]
        self.order = np.argsort(name, kind="stable")
        self.starts = np.searchsorted(name[self.order], np.arange(self.cells[0] * self.cells[1] + 1))

    def around(self, k: int, rings: int) -> tuple[np.ndarray, float]:
        """Points of the cells up to ``rings`` away, by index, and a distance within which all are there."""
        at = (self.xy[k] - self.low) // self.side
        x0, y0 = np.maximum(at - rings, 0)
        x1, y1 = np.minimum(at + rings, self.cells - 1)
        rows = [self.order[self.starts[x * self.cells[1] + y0] : self.starts[x * self.cells[1] + y1 + 1]] for x in range(x0, x1 + 1)]
        whole = x0 == 0 and y0 == 0 and x1 == self.cells[0] - 1 and y1 == self.cells[1] - 1
        return np.sort(np.concatenate(rows)), np.inf if whole else float(rings * self.side)


def partners(xy: np.ndarray, grid: Grid, k: int) -> np.ndarray:
    """``delaunay_partners`` from the points around k. These settle it once they close the cell of
    points nearer to k than to any other, and reach twice as far as that cell's corners."""
    rings = 1
    while True:
        near, reach = grid.around(k, rings)
        if reach == np.inf:
            return near[delaunay_partners(xy[near], int(np.searchsorted(near, k)))]
        if len(near) > AROUND // 2:
            far = corner(xy, near, k)
            if 2 * far * (1 + 1e-6) + 1 < reach:
                return near[delaunay_partners(xy[near], int(np.searchsorted(near, k)))]
        rings = rings + 1 if rings < 4 else rings * 2


def corner(xy: np.ndarray, near: np.ndarray, k: int) -> float:
    """Distance from point k within which its cell among the nearest of ``near`` lies, infinite if
    these leave it open. More points only make the cell smaller."""
    d = (xy[near[near != k]] - xy[k]).astype(float)
    d = d[np.argsort((d**2).sum(axis=1), kind="stable")[:AROUND]]
    half = (d**2).sum(axis=1) / 2
    # where two bisectors cross, and whether all others allow that place
    cross = d[:, None, 0] * d[None, :, 1] - d[:, None, 1] * d[None, :, 0]
    i, j = np.nonzero(cross > 0)
    x = (half[i] * d[j, 1] - half[j] * d[i, 1]) / cross[i, j]
    y = (half[j] * d[i, 0] - half[i] * d[j, 0]) / cross[i, j]
    angle = np.sort(np.arctan2(d[:, 1], d[:, 0]))
    if len(angle) < 3 or np.diff(np.concatenate([angle, angle[:1] + 2 * np.pi])).max() > np.pi - 1e-6:
        return np.inf
    size = half.max()
    kept = (x[:, None] * d[None, :, 0] + y[:, None] * d[None, :, 1] <= half[None, :] * (1 + 1e-9) + 1e-9 * size).all(axis=1)
    return float(np.sqrt((x[kept] ** 2 + y[kept] ** 2).max())) if kept.any() else np.inf


def allowed(a: np.ndarray, b: np.ndarray, c: np.ndarray) -> bool:
    """Whether some circle through a and b has none of the points c inside."""
    ab = b - a
    cross = (ab[0] * (c[:, 1] - a[1]) - ab[1] * (c[:, 0] - a[0])).astype(object)
    dot = ((a[0] - c[:, 0]) * (b[0] - c[:, 0]) + (a[1] - c[:, 1]) * (b[1] - c[:, 1])).astype(object)
    if any(d < 0 for d in dot[cross == 0]):
        return False  # a point between a and b
    left, right = cross > 0, cross < 0
    if not left.any() or not right.any():
        return True
    # c on the left bounds the centre from above by dot/cross, on the right from below
    top_n, top_d = _least(dot[left], cross[left])
    low_n, low_d = _least(dot[right], -cross[right])
    return top_n * low_d + low_n * top_d >= 0


def _least(num, den):
    """The least fraction, by float first and exactly among the close ones."""
    value = num.astype(float) / den.astype(float)
    close = np.flatnonzero(value <= value.min() + 1e-9 * (1 + abs(value.min())))
    best = close[0]
    for k in close[1:]:
        if num[k] * den[best] < num[best] * den[k]:
            best = k
    return int(num[best]), int(den[best])


def passes(a: np.ndarray, b: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Which pairs (a, b) the points c may leave an empty circle, by floats with a margin."""
    b, c = b - a, c - a
    cross = (b[:, :1] * c[None, :, 1] - b[:, 1:] * c[None, :, 0]).astype(float)
    dot = (c[None, :, 0] * (c[None, :, 0] - b[:, :1]) + c[None, :, 1] * (c[None, :, 1] - b[:, 1:])).astype(float)
    with np.errstate(divide="ignore", invalid="ignore"):
        pos = dot / cross
    top = np.where(cross > 0, pos, np.inf).min(axis=1)
    low = np.where(cross < 0, pos, -np.inf).max(axis=1)
    return top >= low - 1e-6 * (1 + np.minimum(np.abs(top), 1e12))


def delaunay_partners(xy: np.ndarray, k: int) -> np.ndarray:
    """Points with a larger index that share a Delaunay edge with point k."""
    a = xy[k]
    gap = ((xy - a) ** 2).sum(axis=1)
    order = np.argsort(gap, kind="stable")
    order = order[order != k]
    out = []
    rest = order[order > k]
    # floats with a margin sort out most pairs, exact integers decide the others
    maybe = rest[passes(a, xy[rest], xy[order[:NEAR]])]
    if len(maybe) > 2 * NEAR:
        # a point at the border has few near points on one side: others far out sort out the rest
        turn = np.linspace(0, 2 * np.pi, 64, endpoint=False)
        outer = xy[np.unique((xy @ np.stack([np.cos(turn), np.sin(turn)])).argmax(axis=0))]
        wide = np.concatenate([xy[order[: 8 * NEAR]], outer, xy[:: max(1, len(xy) // 256)]])
        maybe = np.concatenate([part[passes(a, xy[part], wide)] for part in np.array_split(maybe, len(maybe) // 2048 + 1)])
    others = np.delete(xy, k, axis=0)
    names = np.delete(np.arange(len(xy)), k)
    for j in maybe.tolist():
        c = others[names != j]
        cr = ((xy[j][0] - a[0]) * (c[:, 1] - a[1]) - (xy[j][1] - a[1]) * (c[:, 0] - a[0])).astype(float)
        dt = ((a[0] - c[:, 0]) * (xy[j][0] - c[:, 0]) + (a[1] - c[:, 1]) * (xy[j][1] - c[:, 1])).astype(float)
        with np.errstate(divide="ignore", invalid="ignore"):
            p = dt / cr
        t, w = np.where(cr > 0, p, np.inf).min(), np.where(cr < 0, p, -np.inf).max()
        if t < w - 1e-6 * (1 + abs(t)):
            continue
        tight = c[(cr == 0) | (p <= t + 1e-6 * (1 + abs(t))) & (cr > 0) | (p >= w - 1e-6 * (1 + abs(w))) & (cr < 0)]
        if allowed(a, xy[j], tight):
            out.append(j)
    return np.array(out, np.int64)
