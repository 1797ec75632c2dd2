"""An empty quadtree (cells only) over the plane, from a histogram, and lookups as expressions."""

from __future__ import annotations

import math
from collections import defaultdict
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.cells import axis_cell

MAX_DEPTH, MOST_LEAVES, TABLE_DEPTH = 10, 4096, 8


@dataclass(frozen=True)
class Quadtree:
    x0: float
    y0: float
    x1: float
    y1: float
    leaves: tuple[tuple[int, int, int], ...] = field(repr=False)
    """(depth, ix, iy) of each leaf; empty leaves are kept."""

    @property
    def depth(self) -> int:
        return max(d for d, _, _ in self.leaves)

    @property
    def smallest_diameter(self) -> float:
        return math.hypot(self.x1 - self.x0, self.y1 - self.y0) / (1 << self.depth)

    def _map(self) -> Column:
        pairs = [F.lit(v) for d, ix, iy in self.leaves for v in (_key(d, ix, iy), _key(d, ix, iy))]
        return F.create_map(*pairs)

    def _table(self) -> Column:
        """The leaf of every finest cell as one literal array."""
        d = self.depth
        at = [0] * (1 << 2 * d)
        for depth, ix, iy in self.leaves:
            step = 1 << (d - depth)
            for i in range(ix * step, (ix + 1) * step):
                at[(i << d) + iy * step : (i << d) + (iy + 1) * step] = [_key(depth, ix, iy)] * step
        return F.expr(f"cast(split('{','.join(map(str, at))}', ',') as array<bigint>)")  # folded into a literal

    def _leaf(self, ix: Column, iy: Column) -> Column:
        """Leaf of a finest cell: one array access, or for deep trees the prefixes of every depth that has leaves."""
        finest = self.depth
        if finest <= TABLE_DEPTH:
            return F.get(self._table(), (F.shiftleft(ix, finest) + iy).cast("int"))
        leaves = self._map()
        keys = [F.lit(d).cast("long") * (1 << 52) + F.shiftright(ix, finest - d) * (1 << 26) + F.shiftright(iy, finest - d) for d in sorted({d for d, _, _ in self.leaves}, reverse=True)]
        return F.coalesce(*[F.try_element_at(leaves, k) for k in keys])

    def home_cell(self, x: Column, y: Column) -> Column:
        d = self.depth
        return self._leaf(axis_cell(x, self.x0, self.x1, d), axis_cell(y, self.y0, self.y1, d))

    def touched_cells(self, x: Column, y: Column, eps: float) -> Column:
        """Array of the leaves that the box of half-width eps around a point meets."""
        d, eps = self.depth, F.lit(float(eps))
        xs = F.sequence(axis_cell(x - eps, self.x0, self.x1, d), axis_cell(x + eps, self.x0, self.x1, d))
        ys = F.sequence(axis_cell(y - eps, self.y0, self.y1, d), axis_cell(y + eps, self.y0, self.y1, d))
        return F.array_distinct(F.flatten(F.transform(xs, lambda i: F.transform(ys, lambda j: self._leaf(i, j)))))

    def coarsened(self, least_side: float) -> Quadtree:
        """The tree cut where cells get smaller than least_side, so that a radius meets few cells."""
        side = min(self.x1 - self.x0, self.y1 - self.y0)
        most = 0 if side <= 0 or least_side <= 0 else max(0, min(self.depth, int(math.log2(max(1.0, side / least_side)))))
        if least_side <= 0:
            most = self.depth
        return Quadtree(self.x0, self.y0, self.x1, self.y1, tuple(sorted({(min(d, most), ix >> max(0, d - most), iy >> max(0, d - most)) for d, ix, iy in self.leaves})))

    def as_rows(self) -> list[tuple]:
        w, h = self.x1 - self.x0, self.y1 - self.y0
        return [(d, ix, iy, self.x0 + w * ix / (1 << d), self.y0 + h * iy / (1 << d), self.x0 + w * (ix + 1) / (1 << d), self.y0 + h * (iy + 1) / (1 << d)) for d, ix, iy in self.leaves]


class CellTable:
    """The same lookups on arrays, for kernels: leaves are numbered from 0 as in ``tree.leaves``."""

    def __init__(self, tree: Quadtree):
        self.box, self.depth, self.count = ((tree.x0, tree.x1), (tree.y0, tree.y1)), tree.depth, len(tree.leaves)
        self.table = np.zeros((1 << self.depth, 1 << self.depth), np.int32)
        for k, (d, ix, iy) in enumerate(tree.leaves):
            step = 1 << (self.depth - d)
            self.table[ix * step : (ix + 1) * step, iy * step : (iy + 1) * step] = k

    def _axis(self, v: np.ndarray, low: float, high: float) -> np.ndarray:
        n = 1 << self.depth
        return np.clip(np.floor((v - low) / ((high - low) / n or 1.0)), 0, n - 1).astype(np.int64)

    def home(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        return self.table[self._axis(x, *self.box[0]), self._axis(y, *self.box[1])].astype(np.int64)

    def touched(self, x: np.ndarray, y: np.ndarray, eps: float) -> tuple[np.ndarray, np.ndarray]:
        """(point, leaf) of every leaf that the box of half-width eps around a point meets, each once."""
        (x_low, x_high), (y_low, y_high) = ((self._axis(v - eps, *box), self._axis(v + eps, *box)) for v, box in ((x, self.box[0]), (y, self.box[1])))
        found = []
        for i in range(int((x_high - x_low).max(initial=0)) + 1):
            for j in range(int((y_high - y_low).max(initial=0)) + 1):
                ok = np.flatnonzero((x_low + i <= x_high) & (y_low + j <= y_high))
                found.append(ok * self.count + self.table[x_low[ok] + i, y_low[ok] + j])
        return np.divmod(np.unique(np.concatenate(found)), self.count)


def _key(d: int, ix: int, iy: int) -> int:
    return d * (1 << 52) + ix * (1 << 26) + iy


def build(pts: DataFrame, cap_fraction: float, max_depth: int = MAX_DEPTH, most_leaves: int = MOST_LEAVES) -> Quadtree:
    """Splits cells that hold more than cap_fraction of the points.

    Points are counted in the finest grid by Spark (at most 4^max_depth counts, a bound free of the
    data's size); the recursion over those counts is on the driver. A tree of more than most_leaves
    leaves (a capacity below about 0.1 %) is refused, as its table would no longer be small to broadcast."""
    x0, y0, x1, y1 = pts.agg(F.min("x"), F.min("y"), F.max("x"), F.max("y")).first()
    if x0 is None:
        return Quadtree(0.0, 0.0, 1.0, 1.0, ((0, 0, 0),))
    fine = pts.groupBy(axis_cell(F.col("x"), x0, x1, max_depth).alias("ix"), axis_cell(F.col("y"), y0, y1, max_depth).alias("iy")).agg(F.count("*").alias("n"))
    counts = {(r["ix"], r["iy"]): r["n"] for r in fine.toLocalIterator()}
    levels = [counts]
    for _ in range(max_depth):
        above: dict[tuple[int, int], int] = defaultdict(int)
        for (ix, iy), n in levels[-1].items():
            above[ix >> 1, iy >> 1] += n
        levels.append(above)
    levels.reverse()
    total = levels[0].get((0, 0), 0)
    leaves, open_ = [], [(0, 0, 0)]
    while open_:
        d, ix, iy = open_.pop()
        if d < max_depth and levels[d].get((ix, iy), 0) > cap_fraction * total:
            open_ += [(d + 1, 2 * ix + a, 2 * iy + b) for a in (0, 1) for b in (0, 1)]
        else:
            leaves.append((d, ix, iy))
    if len(leaves) > most_leaves:
        raise ValueError(f"{len(leaves)} leaves at a capacity of {cap_fraction}: more than {most_leaves}")
    return Quadtree(x0, y0, x1, y1, tuple(sorted(leaves)))
