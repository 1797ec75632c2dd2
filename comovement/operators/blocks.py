"""Whole trajectory pairs in blocks: joining pairs that are worked off where they are found.

Pairs are far more than points, so here only points are shuffled. Trajectories are dealt to groups by hash, and each group
is written once to the shared folder (points without numbers are numbered on that way); a block reads the points of two groups (or of one), so it finds every joining pair
between their trajectories and no other. What depends on all pairs of two trajectories (the matches, the misses) is known
inside a block, a few reference trajectories at a time, and only that leaves the task.

A group holds ``GROUP_POINTS``, so a block is bounded; every point is shuffled and written once, and read once for each group.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator, Sequence
from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..params import JoinParams
from ..plans.quadtree import CellTable, Quadtree
from ..sources.scratch import scratch, shuffles_dropped
from ..sources.store import opened
from ..sources.tables import MATCH_COLUMNS
from .pointjoin import _NEAR, _POINT
from .refine import SCHEMA
from .semantics import matching_rows, maximal_rows

GROUP_POINTS, LEAST_GROUPS, CHUNK, PIECE = 750_000, 6, 1 << 21, 1 << 15
"""Points of a group; groups of small inputs; candidates of a chunk, and of what is tested at once."""
STRIPS = 2
"""Strips of time within the tolerance."""


class Side:
    """Points of a group (one at least), sorted by trajectory and number. ``at`` is the place on the trajectory, from 0; where numbers
    are not consecutive it skips one place, so that places are neighbours just when numbers are."""

    def __init__(self, traj: np.ndarray, seq: np.ndarray, t: np.ndarray, x: np.ndarray, y: np.ndarray):
        self.seq, self.t, self.x, self.y, self._packed, n = seq, t, x, y, None, len(traj)
        new = np.append(True, traj[1:] != traj[:-1])
        self.first = np.flatnonzero(new)
        self.names, self.code = traj[self.first], np.cumsum(new) - 1
        step = np.where(np.append(True, np.diff(seq) == 1), 1, 2)
        place = np.cumsum(np.where(new, 1, step))
        self.at = place - place[self.first][self.code]
        ends = np.append(self.first[1:], n) - 1
        self.base, self.last = place[self.first] - 1, seq[ends]
        self.places = int(self.at[ends].max(initial=0)) + 1
        self.seq_at, self.t_at = np.zeros(int(place[-1]), np.int64), np.zeros(int(place[-1]), np.int64)
        self.seq_at[place - 1], self.t_at[place - 1] = seq, t

    def packed(self, shift: int) -> np.ndarray:
        """Trajectory and place of each point as one number; kept for the next call."""
        if self._packed is None or self._packed[0] != shift:
            self._packed = shift, (self.code << shift) | self.at
        return self._packed[1]

    def place(self, code: np.ndarray, seq: np.ndarray) -> np.ndarray:
        """A number of each (trajectory, number of a point), in their order."""
        low = int(self.seq.min())
        return code * np.int64(int(self.seq.max()) - low + 1) + (seq - low)


class Finder:
    """Candidates of a side: dealt to cells (all are one without a tree), in each to strips of time, sorted by x."""

    def __init__(self, side: Side, params: JoinParams, cells: CellTable | None):
        self.params, self.cells = params, cells
        self.width = max(1, -(-params.eps_t_us // STRIPS))
        self.reach = -(-params.eps_t_us // self.width)
        self.t0 = int(side.t.min())
        if cells is None:
            point, cell = np.arange(len(side.t)), 0
        else:
            point, cell = cells.touched(side.x, side.y, params.eps_sp)
        strip = (side.t[point] - self.t0) // self.width
        self.strips = int(strip.max(initial=0)) + 1
        self.values = np.unique(side.x)
        self.step = len(self.values) + 1  # (cell, strip, x) as one number, by the rank of x
        key = (cell * self.strips + strip) * self.step + np.searchsorted(self.values, side.x[point])
        order = np.argsort(key, kind="stable")
        self.key, self.point = key[order], point[order]
        self.t, self.x, self.y = side.t[self.point], side.x[self.point], side.y[self.point]

    def ranges(self, side: Side, start: int, stop: int) -> tuple[np.ndarray, np.ndarray]:
        """(first, number) of the candidates of points start to stop: a row for each strip to look at."""
        t, x, y = side.t[start:stop], side.x[start:stop], side.y[start:stop]
        cell = 0 if self.cells is None else self.cells.home(x, y)
        slack = float(self.params.eps_sp) + (np.abs(x) + self.params.eps_sp) * 1e-12
        low, high = np.searchsorted(self.values, x - slack), np.searchsorted(self.values, x + slack, "right")
        strip = (t - self.t0) // self.width
        here = (cell * self.strips + strip) * self.step
        order = np.argsort(here + low)  # places that are looked up in their order are found faster
        strip, low, high = strip[order], (here + low)[order], (here + high)[order]
        first, number = np.zeros((2, 2 * self.reach + 1, len(x)), np.int64)
        for row, k in enumerate(range(-self.reach, self.reach + 1)):
            ok = (strip + k >= 0) & (strip + k < self.strips)
            f = np.searchsorted(self.key, low + k * self.step)
            first[row, order] = f
            number[row, order] = np.where(ok, np.maximum(np.searchsorted(self.key, high + k * self.step) - f, 0), 0)
        return first, number


def chunks(a: Side, b: Side, same: bool, params: JoinParams, cells: CellTable | None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Rows (of a, of b) of all joining pairs between some trajectories of a and all of b, a's in order; within one group
    (``same``) each pair of trajectories once. Where one trajectory has very many, b's trajectories are taken in turns."""
    return (found for (found,) in chunks_together(a, b, same, params, [cells]))


def chunks_together(a: Side, b: Side, same: bool, params: JoinParams, ways: Sequence[CellTable | None]) -> Iterator[list[tuple[np.ndarray, np.ndarray]]]:
    """``chunks`` of the same trajectories by each of some ways to find candidates; the first one's are counted."""
    finders, near = [Finder(b, params, cells) for cells in ways], _NEAR[params.metric]
    ends = np.append(a.first[1:], len(a.t))
    k = 0
    while k < len(ends):
        # as many trajectories as have some 64k points, then as many of them as stay within a chunk
        last = max(k + 1, int(np.searchsorted(ends, a.first[k] + 65_536, "right")))
        start = int(a.first[k])
        ranges = [finder.ranges(a, start, int(ends[last - 1])) for finder in finders]
        upto = np.cumsum(ranges[0][1].sum(axis=0))
        while k < last:
            done = int(upto[a.first[k] - start - 1]) if a.first[k] > start else 0
            stop = max(k + 1, min(last, k + int(np.searchsorted(upto[ends[k:last] - start - 1], done + CHUNK, "right"))))
            lo, hi = int(a.first[k]) - start, int(ends[stop - 1]) - start
            turns = max(1, math.ceil((int(upto[hi - 1]) - done) / (8 * CHUNK)))
            for turn in range(turns):
                within = (turn * len(b.names) // turns, (turn + 1) * len(b.names) // turns) if turns > 1 else None
                yield [_tested(a, b, finder, near, start + lo, first[:, lo:hi], number[:, lo:hi], same, within) for finder, (first, number) in zip(finders, ranges)]
            k = stop


def _tested(a: Side, b: Side, finder: Finder, near: Callable, start: int, first: np.ndarray, number: np.ndarray, same: bool, within: tuple[int, int] | None):
    eps_t, eps_sp, rows, others = finder.params.eps_t_us, finder.params.eps_sp, [], []
    for strip, (first, number) in enumerate(zip(first, number)):
        timed = (abs(strip - finder.reach) + 1) * finder.width - 1 > eps_t  # else all of the strip is within the tolerance
        row = np.flatnonzero(number)
        first, number, row = first[row], number[row], row + start
        bounds, at = np.concatenate([[0], np.cumsum(number)]), 0
        while at < len(row):
            to = max(at + 1, int(np.searchsorted(bounds, bounds[at] + PIECE, "right")) - 1)
            n, r = number[at:to], row[at:to]
            s = np.arange(bounds[to] - bounds[at])
            s += np.repeat(first[at:to] - (bounds[at:to] - bounds[at]), n)
            ok = near(np.repeat(a.x[r], n) - finder.x[s], np.repeat(a.y[r], n) - finder.y[s], eps_sp)
            if timed:
                ok &= np.abs(np.repeat(a.t[r], n) - finder.t[s]) <= eps_t
            r, s = np.repeat(r, n)[ok], finder.point[s[ok]]
            if same or within:
                keep = a.code[r] < b.code[s] if same else np.ones(len(r), bool)
                if within:
                    keep &= (b.code[s] >= within[0]) & (b.code[s] < within[1])
                r, s = r[keep], s[keep]
            rows.append(r.astype(np.int32))
            others.append(s.astype(np.int32))
            at = to
    return (np.concatenate(rows), np.concatenate(others)) if rows else (np.empty(0, np.int32), np.empty(0, np.int32))


def _bits(n: int) -> int:
    """Bits for places below n and one more that stays unused, so that the last place of a component and the first of
    the next are no neighbours."""
    return int(n).bit_length()


def matches_of(a: Side, b: Side, r: np.ndarray, s: np.ndarray, params: JoinParams) -> pd.DataFrame | None:
    """Maximal matches of joining pairs (rows of a and b) of whole trajectory pairs.

    The rounds of the exact refine on packed numbers: sorted by (component, place, other place), components split where
    places are not consecutive, those that are too short to qualify are dropped (components are independent), and the
    sides take turns until nothing splits."""
    if not len(r):
        return None
    floor, least, many = params.lifespan_floor_us, params.min_points, len(b.names)
    row, end = int(r.min()), int(r.max()) + 1
    low, top = int(a.code[row]), int(a.code[end - 1])
    bits, sides = (_bits(a.places), _bits(b.places)), (a, b)
    pair, k, found = None, 0, []
    fits = lambda n: int(n).bit_length() + sum(bits) < 63
    if key_fits := fits((top - low + 1) * many):
        own = ((a.code[row:end] - low) * np.int64(many) << sum(bits)) | (a.at[row:end] << bits[1])
        key = own[r - row]
        key += b.packed(sum(bits))[s]
    else:
        comp, v, w = (a.code[r] - low) * np.int64(many) + b.code[s], a.at[r], b.at[s]
    while True:
        side, here, there = sides[k % 2], bits[k % 2], bits[1 - k % 2]
        if key_fits:
            key.sort()
            place = key >> there
            first = np.flatnonzero(np.append(True, np.diff(place) > 1))
        else:
            order = np.lexsort((w, v, comp))
            comp, v, w = comp[order], v[order], w[order]
            first = np.flatnonzero(np.append(True, (np.diff(comp) != 0) | (np.diff(v) > 1)))
        last = np.append(first[1:], len(place if key_fits else v)) - 1
        runs = (place[first], place[last]) if key_fits else (v[first], v[last])
        kept = np.flatnonzero(runs[1] - runs[0] >= least - 1)
        v_from, v_to = (e[kept] & ((1 << here) - 1) for e in runs)
        before = runs[0] >> here if key_fits else comp[first]
        of = before[kept] if pair is None else pair[before[kept]]
        base = side.base[(of // many + low) if k % 2 == 0 else of % many]
        lasting = side.t_at[base + v_to] - side.t_at[base + v_from] >= floor
        kept, of, v_from, v_to = kept[lasting], of[lasting], v_from[lasting], v_to[lasting]
        if not len(kept):
            break
        size = last[kept] - first[kept] + 1
        start = np.cumsum(size) - size
        rows = np.repeat(first[kept] - start, size) + np.arange(size.sum())
        if key_fits:
            key = key[rows]
            v, w = (key >> there) & ((1 << here) - 1), key & ((1 << there) - 1)
        else:
            v, w = v[rows], w[rows]
        if k:  # what the other side's round left whole and this one too is a match
            done = (np.bincount(before) == 1)[before[kept]]
            if done.any():
                spans = [(v_from[done], v_to[done]), tuple(f.reduceat(w, start)[done] for f in (np.minimum, np.maximum))]
                found.append((of[done], *spans[k % 2], *spans[1 - k % 2]))
                if done.all():
                    break
                rows = np.repeat(~done, size)
                v, w, size, of = v[rows], w[rows], size[~done], of[~done]
        comp, pair = np.repeat(np.arange(len(size)), size), of
        v, w, k = w, v, k + 1
        if key_fits := fits(len(size)):
            key = (comp << sum(bits)) | (v << bits[1 - k % 2]) | w
    if not found:
        return None
    pair, *spans = map(np.concatenate, zip(*found))
    spans = [spans[:2], spans[2:]]
    out = {}
    code = (pair // many + low, pair % many)
    for name, own, c, (lo, hi) in zip("ab", sides, code, spans):
        base = own.base[c]
        out[f"{name}_traj"] = own.names[c]
        for end, at in (("from", base + lo), ("to", base + hi)):
            out[f"{name}_{end}"], out[f"{name}_t_{end}"] = own.seq_at[at], own.t_at[at]
        out[f"n_{name}"] = hi - lo + 1
    out["lifespan_us"] = np.minimum(out["a_t_to"], out["b_t_to"]) - np.maximum(out["a_t_from"], out["b_t_from"])
    ok = (out["lifespan_us"] >= floor) & (out["n_a"] >= least) & (out["n_b"] >= least)
    turned = out["a_traj"] > out["b_traj"]  # the lesser trajectory is the reference
    m = {"lifespan_us": out["lifespan_us"]}
    for c in ("{}_traj", "{}_from", "{}_to", "{}_t_from", "{}_t_to", "n_{}"):
        m[c.format("r")] = np.where(turned, out[c.format("b")], out[c.format("a")])
        m[c.format("s")] = np.where(turned, out[c.format("a")], out[c.format("b")])
    return pd.DataFrame(m).loc[ok, list(MATCH_COLUMNS)]


def open_edges_of(a: Side, b: Side, r: np.ndarray, s: np.ndarray, params: JoinParams) -> pd.DataFrame:
    """The joining pairs (rows of a and b) of whole trajectory pairs that may be part of a match, the lesser trajectory
    as the reference: those in runs of places, of either side, that are long enough and last long enough. A part of
    a run is no longer than it."""
    low = int(a.code[r].min(initial=0))
    pair = (a.code[r] - low) * np.int64(len(b.names)) + b.code[s]
    for side, rows in ((a, "r"), (b, "s")):
        row = r if rows == "r" else s
        order = np.lexsort((side.at[row], pair))
        r, s, pair, row = r[order], s[order], pair[order], row[order]
        if not len(row):
            break
        first = np.flatnonzero(np.append(True, (np.diff(pair) != 0) | (np.diff(side.at[row]) > 1)))
        last = np.append(first[1:], len(row)) - 1
        ok = (side.at[row[last]] - side.at[row[first]] + 1 >= params.min_points) & (side.t[row[last]] - side.t[row[first]] >= params.lifespan_floor_us)
        keep = np.repeat(ok, last - first + 1)
        r, s, pair = r[keep], s[keep], pair[keep]
    one, other = a.names[a.code[r]], b.names[b.code[s]]
    turned, out = one > other, {}
    for c, left, right in (("traj", one, other), ("seq", a.seq[r], b.seq[s]), ("t", a.t[r], b.t[s])):
        out[f"r_{c}"], out[f"s_{c}"] = np.where(turned, right, left), np.where(turned, left, right)
    return pd.DataFrame(out)


def open_edges(pts: DataFrame, params: JoinParams, tree: Quadtree | None = None, groups: int | None = None) -> DataFrame:
    """Joining pairs of a self-join (r_traj < s_traj) without those that can be part of no match."""
    each = lambda a, b, pairs: (open_edges_of(a, b, r, s, params) for r, s in pairs)
    return by_blocks(pts, params, each, "r_traj long, r_seq long, r_t long, s_traj long, s_seq long, s_t long", tree, groups)


def in_groups(pts: DataFrame, groups: int) -> DataFrame:
    """Points by group, in each by trajectory and number. Points without numbers get them there, those of
    ``with_sequence``, so that they are shuffled once and not by trajectory first."""
    g = F.pmod(F.xxhash64("traj"), F.lit(groups)).cast("int").alias("g")
    if "seq" in pts.columns:
        return pts.select(*_POINT, g).repartitionById(groups, "g").sortWithinPartitions("g", "traj", "seq")
    number = F.row_number().over(Window.partitionBy("g", "traj").orderBy("t", "pid")).cast("long")
    return pts.select("traj", "t", "x", "y", "pid", g).repartitionById(groups, "g").withColumn("seq", number).select(*_POINT, "g")


def dealt(pts: DataFrame, groups: int) -> str:
    """Folder of the points by group, in the shared folder: a file for each group, by trajectory and number."""
    path = scratch(pts.sparkSession, "groups")
    with shuffles_dropped(pts.sparkSession):
        in_groups(pts, groups).write.option("compression", "zstd").partitionBy("g").parquet(path)
    return path


def points_of(spark: SparkSession, path: str) -> DataFrame:
    """All dealt points."""
    return spark.read.schema("traj long, seq long, t long, x double, y double, g int").parquet(path)


def group(path: str, g: int) -> Side | None:
    """A group of dealt points; None without any."""
    import pyarrow.dataset as ds
    from pyarrow import fs

    where, folder = opened(f"{path}/g={g}")
    if where.get_file_info(folder).type != fs.FileType.Directory:
        return None
    rows = ds.dataset(folder, filesystem=where, format="parquet").to_table(columns=list(_POINT), use_threads=False)
    return Side(*[rows[c].to_numpy() for c in _POINT]) if rows.num_rows else None


def body(path: str, groups: int, params: JoinParams, cells: CellTable | None, out: Callable):
    """mapInPandas body over numbers of blocks: ``out(a, b, pairs)`` gives frames (or none) of a block's chunks of pairs."""

    def run(batches):
        low, high = np.triu_indices(groups)
        for block in (k for pdf in batches for k in pdf["id"]):
            a = group(path, low[block])
            b = a if low[block] == high[block] or a is None else group(path, high[block])
            if b is not None:
                yield from (found for found in out(a, b, chunks(a, b, b is a, params, cells)) if found is not None and len(found))

    return run


def groups_of(n: int) -> int:
    """Groups for n points."""
    return max(LEAST_GROUPS, -(-n // GROUP_POINTS))


def by_blocks(pts: DataFrame, params: JoinParams, out: Callable, schema: str, tree: Quadtree | None = None, groups: int | None = None, path: str | None = None) -> DataFrame:
    """What ``out`` makes of the joining pairs of points, whole trajectory pairs at a time; with a tree, points
    are compared by its cells. ``path`` has them where they are dealt to so many groups already."""
    groups = groups or groups_of(pts.count())
    cells, n = None if tree is None else CellTable(tree.coarsened(params.eps_sp)), groups * (groups + 1) // 2
    return pts.sparkSession.range(0, n, 1, n).mapInPandas(body(path or dealt(pts, groups), groups, params, cells, out), schema)


def matches(pts: DataFrame, params: JoinParams, tree: Quadtree | None = None, groups: int | None = None, each: Callable | None = None, schema: str = SCHEMA, path: str | None = None, sides: bool = False, least_us: int | None = None) -> DataFrame:
    """Maximal matches of a self-join, each unordered pair of trajectories once (r_traj < s_traj).

    ``each`` makes frames of ``schema`` of the iterator of a block's frames of matches before they leave the task; a
    frame has all matches of its pairs of trajectories, and a pair stands in one frame. With ``sides`` it gets the block's two
    sides too. ``least_us``: only matches with such a lifespan are asked for; a piece that does not last so long on either
    side has none, so it is dropped as soon as it is seen."""
    asked = params if least_us is None else replace(params, delta_t_us=max(params.delta_t_us, least_us + 2 * params.eps_t_us))

    def out(a: Side, b: Side, pairs):
        found = (m for r, s in pairs if (m := matches_of(a, b, r, s, asked)) is not None and len(m))
        return found if each is None else each(found, a, b) if sides else each(found)

    return by_blocks(pts, params, out, schema, tree, groups, path)


def checked(pts: DataFrame, params: JoinParams, tree: Quadtree | None = None, groups: int | None = None) -> DataFrame:
    """One row: n matches of a self-join, those that pass the definition's matching test by all their joining pairs
    (n_matching), and those that no other contains (n_maximal)."""

    def check(a: Side, b: Side, pairs):
        n = np.zeros(3, np.int64)
        for r, s in pairs:
            m = matches_of(a, b, r, s, params)
            if m is None or not len(m):
                continue
            left, right, q, v = a.names[a.code[r]], b.names[b.code[s]], a.seq[r], b.seq[s]
            turned = left > right
            e = {"r_traj": np.where(turned, right, left), "s_traj": np.where(turned, left, right), "r_seq": np.where(turned, v, q), "s_seq": np.where(turned, q, v)}
            n += len(m), np.count_nonzero(matching_rows(pd.DataFrame(e), m, params)), np.count_nonzero(maximal_rows(m))
        yield pd.DataFrame([n], columns=["n", "n_matching", "n_maximal"])

    found = by_blocks(pts, params, check, "n long, n_matching long, n_maximal long", tree, groups)
    return found.agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in found.columns])


def bag_difference(left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Rows only in left, only in right, in both (as bags), repeated rows of left."""
    values, at = np.unique(np.concatenate([left, right]), return_inverse=True)
    n, m = np.bincount(at[: len(left)], minlength=len(values)), np.bincount(at[len(left) :], minlength=len(values))
    return np.array([np.maximum(n - m, 0).sum(), np.maximum(m - n, 0).sum(), np.minimum(n, m).sum(), np.maximum(n - 1, 0).sum()], np.int64)


def compare_cells(pts: DataFrame, params: JoinParams, tree: Quadtree, groups: int | None = None) -> DataFrame:
    """``general.compare`` of the directed joining pairs of a self-join that are found by time alone and by the tree's
    cells, pair by pair inside the blocks that have both."""
    cells = CellTable(tree.coarsened(params.eps_sp))

    def out(a: Side, b: Side, pairs):
        n = np.zeros(4, np.int64)
        for plain, indexed in chunks_together(a, b, a is b, params, [None, cells]):
            n += 2 * bag_difference(*[r.astype(np.int64) * len(b.t) + s for r, s in (plain, indexed)])  # both directions
        yield pd.DataFrame([n], columns=columns)

    columns = ["only_left", "only_right", "both", "repeated_left"]
    found = by_blocks(pts, params, out, ", ".join(f"{c} long" for c in columns), None, groups)
    return found.agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in columns])


def _beside(a: Side, b: Side, r: np.ndarray, s: np.ndarray) -> Iterator[tuple]:
    """Of the joining pairs (rows of a and b) of whole trajectory pairs, for either side as the reference: the pairs sorted as
    numbers of (trajectory pair, number v of the partner, number of the reference), the bits of the last two, the trajectory
    pairs where they are numbered anew, (first, size) of the stretches of one v, the stretches whose v - 1 and v + 1 are on the partner's
    trajectory and join no point of the reference's, and the rows whose v - 1 is that of another row's v + 1."""
    row, end, many = int(r.min()), int(r.max()) + 1, len(b.names)
    low, total = int(a.code[row]), [_bits(int(side.last.max()) + 2) for side in (a, b)]
    pairs, shift = (int(a.code[end - 1]) - low + 1) * many, sum(total)
    named = comp = None
    if pairs.bit_length() + shift > 62:
        named, comp = np.unique((a.code[r] - low) * np.int64(many) + b.code[s], return_inverse=True)
    for turn, (own, far) in enumerate((total, total[::-1])):
        to_a, to_b = (0, own) if turn == 0 else (own, 0)
        if comp is None:
            key = (((a.code[row:end] - low) * np.int64(many) << shift) | (a.seq[row:end] << to_a))[r - row]
            key += ((b.code << shift) | (b.seq << to_b))[s]
        else:
            key = (comp << shift) | (a.seq[r] << to_a) | (b.seq[s] << to_b)
        key.sort()
        place = key >> own
        first = np.flatnonzero(np.append(True, place[1:] != place[:-1]))
        size = np.diff(first, append=len(key))
        at = place[first]
        gap, v, pair = np.diff(at), at & ((1 << far) - 1), at >> far
        pair = pair if named is None else named[pair]
        one = pair // many
        last = b.last[pair - one * many] if turn == 0 else a.last[one + low]
        before, after = np.append(True, gap != 1) & (v > 1), np.append(gap != 1, True) & (v < last)
        hole = np.flatnonzero(gap == 2) + 1
        n = size[hole]
        rows = np.repeat(first[hole] - (np.cumsum(n) - n), n) + np.arange(n.sum())
        two = key[rows] - (2 << own)
        again = rows[key[np.searchsorted(key, two)] == two]
        yield turn, low, key, own, far, named, first, size, before, after, again


def misses_of(a: Side, b: Side, r: np.ndarray, s: np.ndarray) -> Iterator[pd.DataFrame]:
    """Candidate misses of both directions."""
    if not len(r):
        return
    for turn, low, key, own, far, named, _, size, before, after, again in _beside(a, b, r, s):
        left = np.repeat(before, size)
        left[again] = False
        for step, key in ((-1, key[left]), (1, key[np.repeat(after, size)])):
            pair = key >> (own + far)
            one, other = np.divmod(pair if named is None else named[pair], len(b.names))
            p, x = (a.names[one + low], b.names[other]) if turn == 0 else (b.names[other], a.names[one + low])
            yield pd.DataFrame({"r_traj": p, "r_seq": key & ((1 << own) - 1), "s_traj": x, "s_seq": ((key >> own) & ((1 << far) - 1)) + step})


def count_misses(a: Side, b: Side, r: np.ndarray, s: np.ndarray) -> int:
    """The number of rows of ``misses_of``."""
    return sum(int(size[before].sum() + size[after].sum()) - len(again) for *_, size, before, after, again in _beside(a, b, r, s)) if len(r) else 0


def candidate_misses(pts: DataFrame, params: JoinParams, tree: Quadtree | None = None, groups: int | None = None) -> DataFrame:
    """``classify.candidate_misses`` of a self-join, without its pairs."""
    each = lambda a, b, pairs: (found for r, s in pairs for found in misses_of(a, b, r, s))
    return by_blocks(pts, params, each, "r_traj long, r_seq long, s_traj long, s_seq long", tree, groups)


def _tally(a: Side, b: Side, pairs) -> Iterator[pd.DataFrame]:
    """Directed pairs and misses of a block, and which of its points join: a bit for each point of a group, which its
    first trajectory names, 64 in a row."""
    live, n_jp, n_miss = [np.zeros(-(-len(side.t) // 64) * 64, bool) for side in (a, b)], 0, 0
    for r, s in pairs:
        n_jp, n_miss = n_jp + 2 * len(r), n_miss + count_misses(a, b, r, s)
        live[0][r], live[1][s] = True, True
    yield pd.DataFrame({"traj": [a.names[0]], "word": [-1], "live": [0], "n_jp": [n_jp], "n_miss": [n_miss]})
    for side, on in zip((a, b), live):
        words = np.packbits(on).view(np.int64)
        yield pd.DataFrame({"traj": side.names[0], "word": np.arange(len(words)), "live": words, "n_jp": 0, "n_miss": 0})


def tally(pts: DataFrame, params: JoinParams, tree: Quadtree | None = None, groups: int | None = None) -> DataFrame:
    """One row: n_jp, n_miss (directed pairs, candidate misses) and n_live (points that join) of a self-join."""
    found = by_blocks(pts, params, _tally, "traj long, word long, live long, n_jp long, n_miss long", tree, groups)
    per = found.groupBy("traj", "word").agg(F.sum("n_jp").alias("n_jp"), F.sum("n_miss").alias("n_miss"), F.bit_count(F.bit_or("live")).cast("long").alias("n_live"))
    return per.agg(*[F.coalesce(F.sum(c), F.lit(0).cast("long")).alias(c) for c in ("n_jp", "n_miss", "n_live")])


def both_ways(a: Side, b: Side, pairs, rows: int = 1 << 17) -> Iterator[pd.DataFrame]:
    """The directed joining pairs of a block, some rows at a time."""
    for r, s in pairs:
        for start in range(0, len(r), rows):
            one, other = ({c: getattr(side, c)[at[start : start + rows]] for c in ("code", "seq", "t")} | {"names": side.names} for side, at in ((a, r), (b, s)))
            for left, right in ((one, other), (other, one)):
                yield pd.DataFrame({f"{p}_{c}": v for p, e in (("r", left), ("s", right)) for c, v in (("traj", e["names"][e["code"]]), ("seq", e["seq"]), ("t", e["t"]))})


def _alone(own: Side, others: Iterator[Side], params: JoinParams, cells: CellTable | None, most: int = 8192) -> np.ndarray:
    """Rows of own that join no point of another trajectory. Candidates are tested a few of each point first, and a
    point that joins one is not tested again."""
    alone, near = np.ones(len(own.t), bool), _NEAR[params.metric]
    for other in others:
        finder, left = Finder(other, params, cells), np.flatnonzero(alone)
        for start in range(0, len(left), most):
            row, done, step = left[start : start + most], 0, 16
            first, number = finder.ranges(_Rows(own, row), 0, len(row))
            while len(row):
                r, s = _tested(_Rows(own, row), other, finder, near, 0, first + done, np.clip(number - done, 0, step), False, None)
                joins = np.zeros(len(row), bool)
                joins[r[own.code[row[r]] != own.code[s]] if other is own else r] = True
                alone[row[joins]] = False
                done, step = done + step, min(4 * step, 256)
                more = ~joins & (number > done).any(axis=0)
                row, first, number = row[more], first[:, more], number[:, more]
        if not alone.any():
            break
    return np.flatnonzero(alone)


class _Rows:
    """Some points of a side."""

    def __init__(self, side: Side, row: np.ndarray):
        self.t, self.x, self.y, self.code = side.t[row], side.x[row], side.y[row], side.code[row]


def lone_points(spark: SparkSession, path: str, groups: int, params: JoinParams, tree: Quadtree | None = None) -> DataFrame:
    """traj and seq of the dealt points without any joining pair: a task has a group and reads the others in turn, as long as it
    has points that none has joined."""
    cells = None if tree is None else CellTable(tree.coarsened(params.eps_sp))

    def run(batches):
        for g in (k for pdf in batches for k in pdf["id"]):
            if (own := group(path, g)) is not None:
                each = (own if k == groups else group(path, (g + k) % groups) for k in range(1, groups + 1))
                row = _alone(own, (side for side in each if side is not None), params, cells)
                yield pd.DataFrame({"traj": own.names[own.code[row]], "seq": own.seq[row]})

    return spark.range(0, groups, 1, groups).mapInPandas(run, "traj long, seq long")


def _live(a: Side, b: Side, pairs) -> Iterator[pd.DataFrame]:
    """Points of a block that join some other."""
    live = [np.zeros(len(a.t), bool), np.zeros(len(b.t), bool)]
    for r, s in pairs:
        live[0][r], live[1][s] = True, True
    for side, on in zip((a, b), live):
        yield pd.DataFrame({"traj": side.names[side.code[on]], "seq": side.seq[on]})


def _apart(a: Side, b: Side, params: JoinParams, cells: CellTable | None, most: int) -> Iterator[pd.DataFrame]:
    """The directed pairs of a block's points that do not join, some ``most`` pairs of points at a time, both directions."""
    finder, near, n = Finder(b, params, cells), _NEAR[params.metric], len(b.t)
    step = max(1, most // n)
    for start in range(0, len(a.t), step):
        stop = min(start + step, len(a.t))
        first, number = finder.ranges(a, start, stop)
        far = a.code[start:stop, None] < b.code if b is a else np.ones((stop - start, n), bool)
        r, s = _tested(a, b, finder, near, start, first, number, b is a, None)
        far[r - start, s] = False
        r, s = np.nonzero(far)
        one, other = [(side.names[side.code[row]], side.seq[row]) for side, row in ((a, r + start), (b, s))]
        for left, right in ((one, other), (other, one)):
            yield pd.DataFrame(dict(zip(("r_traj", "r_seq", "s_traj", "s_seq"), (*left, *right))))


def non_joining(pts: DataFrame, params: JoinParams, tree: Quadtree | None = None, groups: int | None = None) -> DataFrame:
    """``classify.non_joining`` of a self-join: a first pass finds the points that join at all, a second gives the others
    of each among them; only points are shuffled, but the result grows with their square."""
    live = by_blocks(pts, params, _live, "traj long, seq long", tree, groups).distinct()
    among = pts.select(*_POINT).join(live, ["traj", "seq"], "left_semi")
    cells, most = None if tree is None else CellTable(tree.coarsened(params.eps_sp)), 8 * PIECE
    return by_blocks(among, params, lambda a, b, pairs: _apart(a, b, params, cells, most), "r_traj long, r_seq long, s_traj long, s_seq long", tree, groups or groups_of(pts.count()))


def count_by_radius(pts: DataFrame, params: JoinParams, radii: Sequence[float], tree: Quadtree | None = None, groups: int | None = None) -> DataFrame:
    """One row: n0, n1, ... directed joining pairs of a self-join for each radius (params has the largest)."""
    near = _NEAR[params.metric]

    def count(a: Side, b: Side, pairs):
        n = np.zeros(len(radii), np.int64)
        for r, s in pairs:
            dx, dy = a.x[r] - b.x[s], a.y[r] - b.y[s]
            n += [2 * int(np.count_nonzero(near(dx, dy, float(e)))) for e in radii]
        yield pd.DataFrame([n], columns=[f"n{k}" for k in range(len(radii))])

    found = by_blocks(pts, params, count, ", ".join(f"n{k} long" for k in range(len(radii))), tree, groups)
    return found.agg(*[F.coalesce(F.sum(f"n{k}"), F.lit(0)).alias(f"n{k}") for k in range(len(radii))])
