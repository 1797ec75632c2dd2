"""Joining pairs: all (ref, other) points of different trajectories within the radius and the tolerance.

Every method returns r_traj, r_seq, r_t, s_traj, s_seq, s_t, each directed pair once: the side that is
the reference stands in its home slab (and bucket, and cell) alone, the other side is replicated to
every key that its tolerance meets. prepart and indexed are equi-joins with the band as residual;
basic sorts stretches of its slabs by time and sweeps them in an Arrow kernel, which holds one stretch;
the sweep, the tile grid, and prepart and indexed on a prepared store sort by time and sweep in one
that holds one batch and the rows within eps_t before it. No method but ``naive``
plans a nested loop, and none needs a distinct.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.distance import CELL_SAFE, WITHIN
from ..params import JoinParams
from ..plans import partitioning, quadtree
from ..plans.partitioning import Slabs
from ..plans.quadtree import CellTable, Quadtree
from ..sources import store
from ..sources.store import PreparedStore

OUT = ("r_traj", "r_seq", "r_t", "s_traj", "s_seq", "s_t")


def _ref(pts: DataFrame, carry: tuple[str, ...] = ()) -> DataFrame:
    return pts.select(*[F.col(c).alias(f"r_{c}") for c in ("traj", "seq", "t", "x", "y", *carry)])


def _other(pts: DataFrame) -> DataFrame:
    return pts.select(*[F.col(c).alias(f"s_{c}") for c in ("traj", "seq", "t", "x", "y")])


def _out(carry: tuple[str, ...]) -> tuple[str, ...]:
    return (*OUT, *(f"r_{c}" for c in carry))


def close(params: JoinParams, same_set: bool = True) -> Column:
    """The residual: both tolerances, and different trajectories in a self-join."""
    near = (F.abs(F.col("r_t") - F.col("s_t")) <= params.eps_t_us) & WITHIN[params.metric](F.col("r_x"), F.col("r_y"), F.col("s_x"), F.col("s_y"), params.eps_sp)
    return near & (F.col("r_traj") != F.col("s_traj")) if same_set else near


def _bucket(t: Column, params: JoinParams) -> Column:
    return F.floor(t / F.lit(max(1, params.eps_t_us))).cast("long")


def naive(left: DataFrame, right: DataFrame, params: JoinParams, same: bool) -> DataFrame:
    return _ref(left).crossJoin(_other(right)).where(close(params, same)).select(*OUT)


def slab_nested_loop(left: DataFrame, right: DataFrame, params: JoinParams, same: bool, slabs: Slabs) -> DataFrame:
    """All pairs of a slab: the cost that the other methods are measured against."""
    a = _ref(left).withColumn("slab", slabs.of(F.col("r_t")))
    wide = partitioning.expand(right, slabs, params.eps_t_us)
    b = wide.select(*[F.col(c).alias(f"s_{c}") for c in ("traj", "seq", "t", "x", "y")], "slab")
    return a.join(b, "slab").where(close(params, same)).select(*OUT)


def slabbed(left: DataFrame, right: DataFrame, params: JoinParams, same: bool, slabs: Slabs, tree: Quadtree | None = None, carry: tuple[str, ...] = ()) -> DataFrame:
    """prepart (by the slabs given), indexed (with a tree), and basic where more columns of the reference are asked for: keys (slab, bucket[, cell]).

    The other side goes to the three time buckets around its own, and of each to the slabs only that both the
    bucket and its tolerance meet, which is one but at slab borders."""
    width = max(1, params.eps_t_us)
    a = _ref(left, carry).withColumn("slab", slabs.of(F.col("r_t"))).withColumn("bucket", _bucket(F.col("r_t"), params))
    own = _bucket(F.col("s_t"), params)
    wide = _other(right).withColumn("bucket", F.explode(F.sequence(own - 1, own + 1)))
    first = F.greatest(F.col("bucket") * width, F.col("s_t") - params.eps_t_us)
    last = F.least(F.col("bucket") * width + (width - 1), F.col("s_t") + params.eps_t_us)
    wide = wide.where(first <= last).withColumn("slab", F.explode(F.sequence(slabs.of(first), slabs.of(last))))
    keys = ["slab", "bucket"]
    if tree is not None:
        if params.metric not in CELL_SAFE:
            raise ValueError(f"{params.metric} cannot be pruned by cells")
        fit = tree.coarsened(params.eps_sp)
        a = a.withColumn("cell", fit.home_cell(F.col("r_x"), F.col("r_y")))
        wide = wide.withColumn("cell", F.explode(fit.touched_cells(F.col("s_x"), F.col("s_y"), params.eps_sp)))
        keys.append("cell")
    wide = wide.withColumnsRenamed({k: f"s_{k}" for k in keys})
    on = close(params, same)
    for k in keys:
        on = (F.col(k) == F.col(f"s_{k}")) & on
    return a.join(wide, on).select(*_out(carry))


_NEAR = {
    "euclid": lambda dx, dy, eps: dx * dx + dy * dy <= eps * eps,
    "manhattan": lambda dx, dy, eps: np.abs(dx) + np.abs(dy) <= eps,
    "chebyshev": lambda dx, dy, eps: np.maximum(np.abs(dx), np.abs(dy)) <= eps,
}
_POINT = ("traj", "seq", "t", "x", "y")
JP_SCHEMA = ", ".join(f"{c} long" for c in OUT)


def _swept(rows: dict[str, np.ndarray], key: np.ndarray, fresh: np.ndarray, params: JoinParams, same: bool, block: int = 65_536):
    """Frames of pairs among rows sorted by (key, t): each point meets the earlier ones of its key within eps_t, found
    by binary search. A directed pair is given where its reference is at home, so each once; one side of it is fresh."""
    t, x, y, traj, home = (rows[c] for c in ("t", "x", "y", "traj", "home"))
    times = np.unique(t)
    step = len(times) + 1  # (key, time) as one number, by the time's rank
    low = np.searchsorted(key * step + np.searchsorted(times, t), key * step + np.searchsorted(times, t - params.eps_t_us))
    counts = np.where(fresh, np.arange(len(t)) - low, 0)
    bounds, start = np.concatenate([[0], np.cumsum(counts)]), 0
    while start < len(t):
        stop = max(start + 1, int(np.searchsorted(bounds, bounds[start] + block, "right")) - 1)
        b = np.repeat(np.arange(start, stop), counts[start:stop])
        a = np.arange(len(b)) - np.repeat(bounds[start:stop] - bounds[start], counts[start:stop]) + low[b]
        near = _NEAR[params.metric](x[a] - x[b], y[a] - y[b], params.eps_sp)
        near &= traj[a] != traj[b] if same else rows["side"][a] != rows["side"][b]
        a, b = a[near], b[near]
        r, s = np.append(a, b), np.append(b, a)
        ok = home[r] if same else home[r] & (rows["side"][r] == 0)
        r, s = r[ok], s[ok]
        if len(r):
            yield pd.DataFrame({"r_traj": traj[r], "r_seq": rows["seq"][r], "r_t": t[r], "s_traj": traj[s], "s_seq": rows["seq"][s], "s_t": t[s]})
        start = stop


def sweep_kernel(params: JoinParams, keys: tuple[str, ...], same: bool = True, cells: CellTable | None = None):
    """mapInPandas body: rows (keys, t, x, y, traj, seq, home[, side]) sorted by (keys, t) to pairs.

    A frame is a batch and, before it, the rows of its first key within eps_t; nothing else is kept. With ``cells``
    the rows of a frame are dealt to every cell they are near, and swept cell by cell."""

    def run(batches):
        held: dict[str, np.ndarray] | None = None
        for pdf in batches:
            rows = {c: pdf[c].to_numpy() for c in pdf.columns}
            old = 0 if held is None else len(held["t"])
            if old:
                rows = {c: np.concatenate([held[c], v]) for c, v in rows.items()}
            n = len(rows["t"])
            if not n:
                continue
            new = np.append(True, np.zeros(n - 1, bool))
            for k in keys:
                new[1:] |= rows[k][1:] != rows[k][:-1]
            key, fresh = np.cumsum(new), np.arange(n) >= old
            if cells is None:
                yield from _swept(rows, key, fresh, params, same)
            else:
                point, cell = cells.touched(rows["x"], rows["y"], params.eps_sp)
                order = np.lexsort((point, cell, key[point]))  # points come by time
                point, cell = point[order], cell[order]
                dealt = {c: v[point] for c, v in rows.items()}
                dealt["home"] = dealt["home"] & (cells.home(dealt["x"], dealt["y"]) == cell)
                yield from _swept(dealt, key[point] * cells.count + cell, fresh[point], params, same)
            keep = (key == key[-1]) & (rows["t"] >= rows["t"][-1] - params.eps_t_us)
            held = {c: v[keep] for c, v in rows.items()}

    return run


STRIPS, SPANS = 4, 4
"""Strips of time within the tolerance; tolerances in a stretch of time that is swept at once."""


def _strips(rows: dict[str, np.ndarray], params: JoinParams, same: bool, piece: int = 1 << 17):
    """Frames of pairs among rows of one stretch of time, sorted by t. Each point meets the later ones within eps_t: in its own
    strip and the following, sorted by x, those within the radius along x are found by binary search. A directed pair is
    given where its reference is at home."""
    t, x, y, traj, home = (rows[c] for c in ("t", "x", "y", "traj", "home"))
    eps_t, eps_sp = params.eps_t_us, float(params.eps_sp)
    width = max(1, -(-eps_t // STRIPS))
    strip = (t - t[0]) // width
    values = np.unique(x)
    step = len(values) + 1  # (strip, x) as one number, by the rank of x
    key = strip * step + np.searchsorted(values, x)
    order = np.argsort(key, kind="stable")
    key, to_t, to_x, to_y, to_traj = key[order], t[order], x[order], y[order], traj[order]
    slack = eps_sp + (np.abs(x) + eps_sp) * 1e-12
    low, high = np.searchsorted(values, x - slack), np.searchsorted(values, x + slack, "right")
    first = np.concatenate([np.searchsorted(key, (strip + k) * step + low) for k in range(-(-eps_t // width) + 1)])
    ends = np.concatenate([np.searchsorted(key, (strip + k) * step + high) for k in range(-(-eps_t // width) + 1)])
    row, number = np.tile(np.arange(len(t)), len(first) // len(t)), np.maximum(ends - first, 0)
    some = number > 0
    row, first, number = row[some], first[some], number[some]
    bounds, at, near = np.concatenate([[0], np.cumsum(number)]), 0, _NEAR[params.metric]
    while at < len(row):
        to = max(at + 1, int(np.searchsorted(bounds, bounds[at] + piece, "right")) - 1)
        n, a = number[at:to], row[at:to]
        b = np.arange(bounds[to] - bounds[at])
        b += np.repeat(first[at:to] - (bounds[at:to] - bounds[at]), n)
        ok = near(np.repeat(x[a], n) - to_x[b], np.repeat(y[a], n) - to_y[b], eps_sp)
        ok &= to_t[b] - np.repeat(t[a], n) <= eps_t
        hit = np.flatnonzero(ok)
        a, b = np.repeat(a, n)[hit], order[b[hit]]
        ok = a < b  # by place in time: the earlier of the own strip are met from there
        ok &= traj[a] != traj[b] if same else rows["side"][a] != rows["side"][b]
        a, b = a[ok], b[ok]
        r, s = np.append(a, b), np.append(b, a)
        ok = home[r] if same else home[r] & (rows["side"][r] == 0)
        r, s = r[ok], s[ok]
        if len(r):
            yield pd.DataFrame({"r_traj": traj[r], "r_seq": rows["seq"][r], "r_t": t[r], "s_traj": traj[s], "s_seq": rows["seq"][s], "s_t": t[s]})
        at = to


def strip_kernel(params: JoinParams, same: bool):
    """mapInPandas body: rows (slab, span, t, x, y, traj, seq, home[, side]) sorted by (slab, span, t) to pairs; it holds the
    rows of one stretch of a slab."""

    def run(batches):
        held: list[dict[str, np.ndarray]] = []

        def swept():
            yield from _strips({c: np.concatenate([h[c] for h in held]) for c in held[0]}, params, same)
            held.clear()

        for pdf in batches:
            rows = {c: pdf[c].to_numpy() for c in pdf.columns}
            cuts = np.flatnonzero((np.diff(rows["slab"]) != 0) | (np.diff(rows["span"]) != 0)) + 1
            for lo, hi in zip([0, *cuts], [*cuts, len(pdf)]):
                part = {c: v[lo:hi] for c, v in rows.items()}
                if held and len(part["t"]) and (held[-1]["slab"][-1], held[-1]["span"][-1]) != (part["slab"][0], part["span"][0]):
                    yield from swept()
                if len(part["t"]):
                    held.append(part)
        if held:
            yield from swept()

    return run


def basic(left: DataFrame, right: DataFrame, params: JoinParams, same: bool, slabs: Slabs) -> DataFrame:
    """The slabs given, each expanded by its tolerance and cut into stretches of some tolerances; a stretch is sorted by time
    and swept. A point goes to the stretches that its tolerance meets, and is a reference in its own alone."""
    width = SPANS * max(1, params.eps_t_us)
    first, last = F.col("t") - params.eps_t_us, F.col("t") + params.eps_t_us
    span = lambda c: F.floor(c / F.lit(width)).cast("long")
    wide = _sides(left, right, same).withColumn("span", F.explode(F.sequence(span(first), span(last))))
    first, last = F.greatest(F.col("span") * width, first), F.least(F.col("span") * width + (width - 1), last)
    wide = wide.withColumn("slab", F.explode(F.sequence(slabs.of(first), slabs.of(last))))
    home = (F.col("slab") == slabs.of(F.col("t"))) & (F.col("span") == span(F.col("t")))
    n_parts = max(slabs.count, int(left.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    dealt = wide.select("slab", "span", *_POINT, "side", home.alias("home"), F.pmod("span", F.lit(n_parts)).cast("int").alias("part"))
    return dealt.repartitionById(n_parts, "part").drop("part").sortWithinPartitions("slab", "span", "t").mapInPandas(strip_kernel(params, same), JP_SCHEMA)


def _sides(left: DataFrame, right: DataFrame, same: bool) -> DataFrame:
    """The points to sweep: those of a self-join once, else both relations with their side."""
    one = left.select(*_POINT, F.lit(0).alias("side"))
    return one if same else one.unionByName(right.select(*_POINT, F.lit(1).alias("side")))


def gridtile(left: DataFrame, right: DataFrame, params: JoinParams, same: bool, box: tuple, dedupe: str = "home", nx: int | None = None, ny: int | None = None, nt: int | None = None, n_parts: int | None = None) -> DataFrame:
    """A fine uniform grid over space and time: every point is copied to each tile that its tolerances meet, tiles are
    mapped to partitions by their hash, sorted by time and swept. A pair is given in the tile where its reference
    is at home, or made distinct.

    box: least x, y, t and greatest x, y, t; nx, ny, nt tiles along each axis (None: of twice the tolerance)."""
    x0, y0, t0, x1, y1, t1 = box
    side = lambda low, high, n, eps: max(2 * eps, 1e-9) if n is None else max((high - low) / n, 1e-9)
    w = {"x": side(x0, x1, nx, float(params.eps_sp)), "y": side(y0, y1, ny, float(params.eps_sp)), "t": max(1, 2 * params.eps_t_us if nt is None else -(-(t1 - t0 + 1) // nt))}
    low, eps = {"x": x0, "y": y0, "t": t0}, {"x": float(params.eps_sp), "y": float(params.eps_sp), "t": params.eps_t_us}
    cell = lambda c, v: F.floor((v - F.lit(low[c])) / F.lit(w[c])).cast("long")
    wide, home = _sides(left, right, same), F.lit(True)
    for c in ("x", "y", "t"):
        wide = wide.withColumn(f"h{c}", cell(c, F.col(c))).withColumn(f"g{c}", F.explode(F.sequence(cell(c, F.col(c) - F.lit(eps[c])), cell(c, F.col(c) + F.lit(eps[c])))))
        home = home & (F.col(f"g{c}") == F.col(f"h{c}"))
    tile = ("gx", "gy", "gt")
    n_parts = n_parts or int(left.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    wide = wide.select(*tile, *_POINT, "side", (home if dedupe == "home" else F.lit(True)).alias("home"), F.pmod(F.xxhash64(*tile), F.lit(n_parts)).cast("int").alias("part"))
    dealt = wide.repartitionById(n_parts, "part").drop("part").sortWithinPartitions(*tile, "t")
    found = dealt.mapInPandas(sweep_kernel(params, tile, same), JP_SCHEMA)
    return found if dedupe == "home" else found.distinct()


def sweep(left: DataFrame, right: DataFrame, params: JoinParams, same: bool, slabs: Slabs) -> DataFrame:
    """The sweep over expanded slabs, each in one stream of points by time; a self-join or two relations."""
    wide = partitioning.expand(_sides(left, right, same), slabs, params.eps_t_us).withColumnRenamed("is_home", "home").drop("home_slab")
    return wide.repartition("slab").sortWithinPartitions("slab", "t").mapInPandas(sweep_kernel(params, ("slab",), same), JP_SCHEMA)


def stored(spark: SparkSession, prepared: PreparedStore, params: JoinParams, spatial_index: bool, traj_index: bool = True) -> DataFrame:
    """prepart and indexed on a prepared store: every task reads its slab as it lies and the neighbours' rows within
    eps_t, and sweeps them, cell by cell with the spatial index: no shuffle.

    Without the trajectory index the stored numbering is not read: points are numbered anew and joined to the rows of the
    slabs, which are shuffled for that; pairs never are."""
    cells = CellTable(prepared.tree.coarsened(params.eps_sp)) if spatial_index else None
    rows = store.halo(spark, prepared, params)
    if not traj_index:
        w = Window.partitionBy("traj").orderBy("t", "pid")
        numbered = prepared.points(spark).select("traj", "t", "pid", F.row_number().over(w).cast("long").alias("seq"))
        joined = rows.drop("seq").join(numbered, ["traj", "t", "pid"])
        rows = joined.repartitionById(prepared.slabs.count, "slab").sortWithinPartitions("slab", "t", "pid")
    found = rows.select("slab", "t", "x", "y", "traj", F.col("is_home").alias("home"), "seq")
    return found.mapInPandas(sweep_kernel(params, ("slab",), True, cells), JP_SCHEMA)


def pairs_and_breaks(pts: DataFrame, params: JoinParams, cap_fraction: float = 0.03, groups: int | None = None) -> DataFrame:
    """Joining pairs of a self-join and its breaking points, with kind JP or BP: the indexed join as an outer one, in blocks
    (``blocks``), so that neither pairs nor copies of points are shuffled. Points may be without numbers."""
    from . import blocks

    spark, groups = pts.sparkSession, groups or blocks.groups_of(pts.count())
    path = blocks.dealt(pts, groups)
    own = blocks.points_of(spark, path)
    tree = quadtree.build(own, cap_fraction)
    found = blocks.by_blocks(own, params, blocks.both_ways, JP_SCHEMA, tree, groups, path)
    # as few rows as it may be taken for, it can be nearly all points: no broadcast by that guess
    lone = own.join(blocks.lone_points(spark, path, groups, params, tree).hint("merge"), ["traj", "seq"], "left_semi")
    none = [F.lit(None).cast("long").alias(f"s_{c}") for c in ("traj", "seq", "t")]
    breaks = lone.select(*[F.col(c).alias(f"r_{c}") for c in ("traj", "seq", "t")], *none)
    return found.withColumn("kind", F.lit("JP")).unionByName(breaks.withColumn("kind", F.lit("BP")))


def joining_pairs(left: DataFrame, right: DataFrame | None, params: JoinParams, method: str = "indexed", n_slabs: int = 16, slabs: Slabs | None = None, tree: Quadtree | None = None, cap_fraction: float = 0.03, carry: tuple[str, ...] = (), **tiles) -> DataFrame:
    """Joining pairs of numbered points (with seq) by the method named; right=None is the self-join. ``carry`` names
    more columns of the reference to return (basic, prepart, indexed); ``tiles`` are gridtile's own."""
    same, other = right is None, left if right is None else right
    if method == "naive":
        return naive(left, other, params, same)
    every = left if same else left.select("t", "x", "y").unionByName(other.select("t", "x", "y"))
    if method == "gridtile":
        box = every.agg(*[f(c) for f in (F.min, F.max) for c in ("x", "y", "t")]).first()
        return gridtile(left, other, params, same, tuple(0 if v is None else v for v in box), **tiles)
    if slabs is None:
        slabs = partitioning.equi_depth(every, n_slabs) if method in ("prepart", "indexed") else partitioning.uniform(every, n_slabs)
    if method == "slab_nested_loop":
        return slab_nested_loop(left, other, params, same, slabs)
    if method == "sweep":
        return sweep(left, other, params, same, slabs)
    if method == "indexed":
        return slabbed(left, other, params, same, slabs, tree or quadtree.build(every, cap_fraction), carry)
    if method == "basic" and not carry and params.metric in _NEAR:
        return basic(left, other, params, same, slabs)
    if method in ("basic", "prepart"):
        return slabbed(left, other, params, same, slabs, None, carry)
    raise ValueError(f"no method {method!r}")
