"""The k nearest points of other trajectories within a time tolerance, without their candidates in a shuffle.

Points are dealt to slabs of time with everything within the tolerance, so a slab knows all candidates of its own
points. Inside a slab a point looks at the cells of a uniform grid around its own, of the times within the tolerance
only; where they hold fewer than k within the cells' side, it looks again with cells of twice the side.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import partitioning

_POINT = ("traj", "seq", "t", "x", "y")
SCHEMA = "r_traj long, r_seq long, s_traj long, s_seq long, d2 double, rank long"
LEAST_SLABS, SLAB_POINTS, PIECE = 16, 200_000, 1 << 20
"""Slabs of small inputs; points that a slab owns; candidates looked at in one go."""


def knn(left: DataFrame, right: DataFrame, k: int, eps_t_us: int) -> DataFrame:
    """k spatially nearest points of other trajectories within the time tolerance (r_/s_ columns), ties by the other's
    trajectory and number."""
    every = left.select("t") if left is right else left.select("t").unionByName(right.select("t"))
    slabs = partitioning.equi_depth(every, max(LEAST_SLABS, -(-every.count() // SLAB_POINTS)))
    wide = partitioning.expand(right.select(*_POINT), slabs, eps_t_us).select("slab", *_POINT, (F.col("is_home") if left is right else F.lit(False)).alias("asked"), F.lit(True).alias("given"))
    if left is not right:
        wide = wide.unionByName(left.select(slabs.of(F.col("t")).alias("slab"), *_POINT, F.lit(True).alias("asked"), F.lit(False).alias("given")))
    return wide.repartitionById(slabs.count, "slab").sortWithinPartitions("slab").mapInPandas(body(k, eps_t_us), SCHEMA)


def body(k: int, eps_t_us: int):
    """mapInPandas body: rows sorted by slab, a slab at a time."""

    def run(batches):
        held: list[pd.DataFrame] = []
        for pdf in batches:
            for slab, rows in pdf.groupby("slab"):
                if held and held[-1]["slab"].iat[0] != slab:
                    yield from _of_slab(pd.concat(held), k, eps_t_us)
                    held = []
                held.append(rows)
        if held:
            yield from _of_slab(pd.concat(held), k, eps_t_us)

    return run


def _of_slab(rows: pd.DataFrame, k: int, eps_t_us: int) -> Iterator[pd.DataFrame]:
    r, s = ({c: rows[c].to_numpy()[rows[side].to_numpy()] for c in _POINT} for side in ("asked", "given"))
    if not len(r["t"]) or not len(s["t"]):
        return
    times = np.unique(s["t"])
    low, high, rank = np.searchsorted(times, r["t"] - eps_t_us), np.searchsorted(times, r["t"] + eps_t_us, "right"), np.searchsorted(times, s["t"])
    reach, span, origin = _start(s, k, 2 * eps_t_us)
    left = np.arange(len(r["t"]))
    while len(left):
        last = not reach < span  # cells of that side are no help: all within the tolerance are looked at
        step = len(times) + 1
        cells = int(min(1 << 20, ((1 << 62) // step) ** 0.5 - 2))
        at = lambda p: 0 * p["t"] if last else sum(_cell(p[c], o, reach, cells) * m for c, o, m in zip("xy", origin, (cells + 2, 1)))  # noqa: B023, E731
        key = at(s) * step + rank
        order = np.argsort(key, kind="stable")
        key, home = key[order], at({c: v[left] for c, v in r.items()})
        around = [0] if last else [i * (cells + 2) + j for i in (-1, 0, 1) for j in (-1, 0, 1)]
        first = np.array([np.searchsorted(key, (home + d) * step + low[left]) for d in around])
        number = np.array([np.searchsorted(key, (home + d) * step + high[left]) for d in around]) - first
        upto, start, unsettled = np.cumsum(number.sum(axis=0)), 0, []
        limit = np.inf if last else (reach * (1 - 1e-6)) ** 2  # the least bit less than the cells' side, for rounding
        while start < len(left):
            done = int(upto[start - 1]) if start else 0
            stop = max(start + 1, int(np.searchsorted(upto, done + PIECE, "right")))
            n = number[:, start:stop].ravel()
            row = np.repeat(np.tile(np.arange(start, stop), len(around)), n)
            to = order[np.arange(len(row)) - np.repeat(np.cumsum(n) - n - first[:, start:stop].ravel(), n)]
            own = left[row]
            with np.errstate(over="ignore", invalid="ignore"):
                dx, dy = r["x"][own] - s["x"][to], r["y"][own] - s["y"][to]
                d2 = dx * dx + dy * dy
            ok = (r["traj"][own] != s["traj"][to]) & (d2 <= limit if not last else True)
            enough = np.bincount(row[ok] - start, minlength=stop - start) >= (0 if last else k)
            unsettled.append(left[start:stop][~enough])
            ok = np.flatnonzero(ok & enough[row - start])
            yield _first(r, s, own[ok], to[ok], d2[ok], k)
            start = stop
        left, reach = np.concatenate(unsettled), reach * 2


def _start(s: dict[str, np.ndarray], k: int, window: int) -> tuple[float, float, tuple[float, float]]:
    """A radius that finds some k points in the middle of the data, the extent of the data, and its lower corner."""
    sides, span, origin = [], 0.0, []
    for c in "xy":
        v = s[c][np.isfinite(s[c])]
        if not len(v):
            return np.inf, 0.0, (0.0, 0.0)
        lo, q1, q3, hi = (float(q) for q in np.quantile(v, [0, 0.25, 0.75, 1]))
        sides.append((q3 - q1) or (hi - lo))
        span, _ = max(span, hi - lo), origin.append(lo)
    among = max(1.0, len(s["t"]) * min(1.0, (window + 1) / (int(s["t"].max()) - int(s["t"].min()) + 1)))
    area = (sides[0] or 1.0) * (sides[1] or 1.0)
    return max((2 * k * area / among) ** 0.5, span * 1e-9), span * 1.01, (origin[0], origin[1])


def _cell(v: np.ndarray, low: float, side: float, cells: int) -> np.ndarray:
    """Number of a cell on an axis, from 1; all beyond the last are in it."""
    return np.clip(np.floor((v - low) / side), 0, cells - 1).astype(np.int64) + 1


def _first(r: dict[str, np.ndarray], s: dict[str, np.ndarray], own: np.ndarray, to: np.ndarray, d2: np.ndarray, k: int) -> pd.DataFrame:
    """The first k of each point by distance, trajectory and number."""
    order = np.lexsort((s["seq"][to], s["traj"][to], d2, own))
    own, to, d2 = own[order], to[order], d2[order]
    new = np.append(True, own[1:] != own[:-1])[: len(own)]
    first = np.flatnonzero(new)
    rank = np.arange(len(own)) - np.repeat(first, np.diff(np.append(first, len(own))))
    keep = rank < k
    own, to = own[keep], to[keep]
    return pd.DataFrame({"r_traj": r["traj"][own], "r_seq": r["seq"][own], "s_traj": s["traj"][to], "s_seq": s["seq"][to], "d2": d2[keep], "rank": rank[keep] + 1})
