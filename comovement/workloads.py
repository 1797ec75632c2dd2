"""The experiment workloads: parameter sweeps as counts, and timed runs of the methods."""

from __future__ import annotations

import math
from collections.abc import Iterable
from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import metrics, points
from .engine import SubtrajectoryJoin
from .operators import blocks, pointjoin, refine
from .params import HOUR, JoinParams
from .plans import partitioning, quadtree
from .sources import store

EPS_T_MINUTES = (60, 90, 120, 150, 180)
EPS_SP = (1.5625, 3.125, 4.6875, 6.25, 7.8125, 10.0, 20.0)
DELTA_T_HOURS = (0, 4, 5, 6, 7, 8, 9)
CAPACITY_PERCENT = (1, 2, 3, 4, 5)


def _union(parts: Iterable[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def vary_eps_t(pts: DataFrame, eps_sp: float = 10.0, minutes: Iterable[int] = EPS_T_MINUTES) -> DataFrame:
    """Joining pairs for each time tolerance. One join at the largest tolerance answers all smaller ones."""
    minutes = sorted(minutes)
    jp = pointjoin.joining_pairs(pts, None, JoinParams(eps_sp, minutes[-1] * 60_000_000), "indexed")
    least = F.abs(F.col("r_t") - F.col("s_t"))
    counts = jp.agg(*[F.count_if(least <= m * 60_000_000).alias(f"m{m}") for m in minutes])
    return counts.select(F.explode(F.array(*[F.struct(F.lit(m).cast("long").alias("eps_t_min"), F.col(f"m{m}").alias("n_jp")) for m in minutes])).alias("r")).select("r.*")


def vary_eps_sp(pts: DataFrame, eps_t_us: int = 2 * HOUR, radii: Iterable[float] = EPS_SP) -> DataFrame:
    """Joining pairs for each radius. One join at the largest radius answers all smaller ones, counted in its blocks."""
    radii = [float(e) for e in radii]
    n = blocks.count_by_radius(pts, JoinParams(max(radii), eps_t_us), radii, quadtree.build(pts, 0.03))
    return n.select(F.explode(F.array(*[F.struct(F.lit(e).alias("eps_sp"), F.col(f"n{k}").alias("n_jp")) for k, e in enumerate(radii)])).alias("r")).select("r.*")


def vary_delta_t(pts: DataFrame, eps_sp: float = 10.0, eps_t_us: int = 2 * HOUR, hours: Iterable[int] = DELTA_T_HOURS) -> DataFrame:
    """Pairs (which stay) and matches (which fall) for each least duration: one refine, then filters, as the
    duration test comes after the components are known."""
    jp = pointjoin.joining_pairs(pts, None, JoinParams(eps_sp, eps_t_us), "indexed").where("r_traj < s_traj")
    n_jp = jp.agg(F.count("*").alias("n_jp"))
    m = refine.maximal_matches(jp, JoinParams(eps_sp, eps_t_us))
    counts = m.agg(*[F.count_if(F.col("lifespan_us") >= JoinParams(eps_sp, eps_t_us, h * HOUR).lifespan_floor_us).alias(f"h{h}") for h in hours])
    both = counts.join(F.broadcast(n_jp))  # one row each
    return both.select(F.explode(F.array(*[F.struct(F.lit(h).cast("long").alias("delta_t_h"), "n_jp", F.col(f"h{h}").alias("n_matches")) for h in hours])).alias("r")).select("r.*")


def vary_capacity(pts: DataFrame, percents: Iterable[int] = CAPACITY_PERCENT) -> DataFrame:
    """Leaves and depth of the tree for each capacity."""
    rows = [(c, len(tree.leaves), tree.depth) for c in percents for tree in [quadtree.build(pts, c / 100)]]
    return pts.sparkSession.createDataFrame(rows, "capacity_pct long, leaves long, depth long")


def vary_size(pts: DataFrame, params: JoinParams, fifths: Iterable[int] = (1, 2, 3, 4, 5)) -> DataFrame:
    """Points and joining pairs of nested portions."""

    def one(i: int) -> DataFrame:
        part = points.with_sequence(points.portion(pts, i))
        n = part.agg(F.count("*").alias("n_points"))
        jp = pointjoin.joining_pairs(part, None, params, "indexed").agg(F.count("*").alias("n_jp"))
        return n.join(F.broadcast(jp)).select(F.lit(i).cast("long").alias("fifths"), "n_points", "n_jp")  # one row each

    return _union(one(i) for i in fifths)


def portion_balance(pts: DataFrame, fifths: Iterable[int] = (1, 2, 3, 4, 5), n_slabs: int = 16) -> DataFrame:
    """Spread of uniform and of equi-depth slabs' sizes for each portion."""

    def one(i: int) -> DataFrame:
        part = points.portion(pts, i)
        uniform = metrics.balance(metrics.slab_sizes(part, partitioning.uniform(part, n_slabs))).select(F.lit(i).cast("long").alias("fifths"), F.lit("uniform").alias("kind"), "sigma", "mean")
        return uniform.unionByName(metrics.balance(partitioning.equi_depth_exact(part, n_slabs)).select(F.lit(i).cast("long").alias("fifths"), F.lit("equi-depth").alias("kind"), "sigma", "mean"))

    return _union(one(i) for i in fifths)


PERCENT = (10, 20, 30, 40, 50)
"""Radii as shares of the smallest cell's diameter."""


def _phases(engine: SubtrajectoryJoin, pts: DataFrame, path: str, prepared=None) -> dict:
    """Join and Refine seconds and counts of one query; the pairs are written in between."""
    numbered = points.with_sequence(pts) if prepared is None else prepared.points(pts.sparkSession)
    row: dict = {}
    row["join_s"], row["n_jp"] = metrics.timed(lambda: _kept(engine.pairs(numbered, None, prepared), path))
    row["refine_s"], row["n_matches"] = metrics.timed(lambda: engine._refined(pts.sparkSession.read.parquet(path), numbered, None))
    return row


def _prepared(method: str, pts: DataFrame, path: str, capacity: float = 0.03):
    """(seconds, store) of the preparation of methods that have one."""
    if method not in ("prepart", "indexed"):
        return None, None
    seconds, _ = metrics.timed(lambda: store.prepare(pts, path, cap_fraction=capacity).points(pts.sparkSession))
    return seconds, store.load(pts.sparkSession, path)


def _warm(pts: DataFrame, params: JoinParams) -> None:
    """A fifth of the points goes through the join first, so that no method pays for the JVM's warm-up."""
    metrics.timed(lambda: SubtrajectoryJoin(params, "indexed").run(points.portion(pts, 1)))


def timings(pts: DataFrame, params: JoinParams, path: str, methods: Iterable[str] = ("basic", "prepart", "indexed")) -> list[dict]:
    """Seconds of preparation, Join and Refine of each method, with counts."""
    _warm(pts, params)
    out = []
    for method in methods:
        once, prepared = _prepared(method, pts, f"{path}/{method}")
        row = {"method": method} | ({} if once is None else {"prepare_s": once})
        out.append(row | _phases(SubtrajectoryJoin(params, method), pts, f"{path}/jp-{method}", prepared))
    return out


def vary_timed(pts: DataFrame, name: str, values: Iterable, path: str, params: JoinParams, methods: Iterable[str] = ("prepart", "indexed")) -> list[dict]:
    """Join and Refine seconds for each value of one parameter (eps_t_us, eps_sp, delta_t_us), on stores prepared once.
    None for eps_sp is the whole plane, where the spatial index cannot prune."""
    _warm(pts, params)
    stores = {m: _prepared(m, pts, f"{path}/{m}")[1] for m in methods}
    box = next((p.tree for p in stores.values() if p is not None), None)
    out = []
    for k, value in enumerate(values):
        value = math.hypot(box.x1 - box.x0, box.y1 - box.y0) if value is None else value
        for m in methods:
            row = _phases(SubtrajectoryJoin(replace(params, **{name: value}), m), pts, f"{path}/{m}-{name}-{k}", stores[m])
            out.append({"method": m, name: value} | row)
    return out


def radii(pts: DataFrame, capacity: float = 0.03, percent: Iterable[int] = PERCENT) -> list[float]:
    """Radii as shares of the diameter of the tree's smallest cell."""
    smallest = quadtree.build(pts, capacity).smallest_diameter
    return [smallest * p / 100 for p in percent]


def _kept(df: DataFrame, path: str) -> DataFrame:
    df.write.parquet(path)
    return df.sparkSession.read.parquet(path)


def slowdown(pts: DataFrame, params: JoinParams, path: str, fifths: Iterable[int] = (1, 2, 3, 4, 5), methods: Iterable[str] = ("basic", "prepart", "indexed")) -> list[dict]:
    """timings() of nested portions; slow_down is the time over that of the smallest portion."""
    rows, first = [], {}
    for i in fifths:
        for row in timings(points.portion(pts, i), params, f"{path}/{i}", methods):
            total = row["join_s"] + row["refine_s"]
            first.setdefault(row["method"], total)
            rows.append(row | {"fifths": i, "slow_down": total / first[row["method"]]})
    return rows


def versus_grid(pts: DataFrame, params: JoinParams, path: str, fifths: Iterable[int] = (1, 2, 3, 4, 5)) -> list[dict]:
    """Join seconds of indexed and of the tile grid (which deals all points anew each time), delta_t = 0."""
    rows = slowdown(pts, JoinParams(params.eps_sp, params.eps_t_us), path, fifths, ("indexed", "gridtile"))
    return [{k: row[k] for k in ("method", "fifths", "join_s", "n_jp")} for row in rows]


def amortised(pts: DataFrame, queries: list[JoinParams], path: str, methods: Iterable[str] = ("basic", "prepart", "indexed")) -> list[dict]:
    """Cumulated seconds after each of several queries of different parameters, each run: basic pays none up front,
    prepart and indexed the preparation, once."""
    _warm(pts, queries[0])
    out = []
    for method in methods:
        once, prepared = _prepared(method, pts, f"{path}/{method}")
        total = once or 0.0
        for q, params in enumerate(queries, 1):
            row = _phases(SubtrajectoryJoin(params, method), pts, f"{path}/{method}-{q}", prepared)
            total += row["join_s"] + row["refine_s"]
            out.append({"method": method, "queries": q, "prepare_s": once or 0.0, "total_s": total, "n_jp": row["n_jp"]})
    return out


def speedup(seconds_by_cores: dict[int, float]) -> list[dict]:
    """The falling ratio T(N) / T(least N), and its reciprocal."""
    base = seconds_by_cores[min(seconds_by_cores)]
    return [{"cores": n, "seconds": s, "ratio": s / base, "speed_up": base / s} for n, s in sorted(seconds_by_cores.items())]


def index_cost(pts: DataFrame, params: JoinParams, path: str, percents: Iterable[int] = CAPACITY_PERCENT) -> list[dict]:
    """For each capacity the seconds to build the spatial index (cells, and every point in the cells it is near) and the
    trajectory index (the numbering), the Join's, and the bytes of both indexes and of the points as written."""
    spark, out = pts.sparkSession, []

    def bytes_of(df: DataFrame, name: str) -> tuple[float, int]:
        seconds, _ = metrics.timed(lambda: _kept(df, f"{path}/{name}"))
        hadoop = spark._jvm.org.apache.hadoop.fs.Path(f"{path}/{name}")
        return seconds, hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(hadoop).getLength()

    _, point_bytes = bytes_of(pts, "points")
    trajectory_s, trajectory_bytes = bytes_of(points.with_sequence(pts).select("traj", "seq", "t"), "trajectory-index")
    for c in percents:
        tree_s, _ = metrics.timed(lambda: vary_capacity(pts, (c,)))  # noqa: B023
        tree = quadtree.build(pts, c / 100)
        cells_s, spatial_bytes = bytes_of(pts.select(F.explode(tree.touched_cells(F.col("x"), F.col("y"), params.eps_sp)).alias("cell"), "t", "pid"), f"spatial-index-{c}")
        prepared = _prepared("indexed", pts, f"{path}/store-{c}", c / 100)[1]
        row = _phases(SubtrajectoryJoin(params, "indexed"), pts, f"{path}/jp-{c}", prepared)
        build_s = tree_s + cells_s + trajectory_s
        out.append({
            "capacity_pct": c, "spatial_build_s": tree_s + cells_s, "trajectory_build_s": trajectory_s, "join_s": row["join_s"], "build_over_join": build_s / row["join_s"],
            "spatial_bytes": spatial_bytes, "trajectory_bytes": trajectory_bytes, "point_bytes": point_bytes, "size_over_points": (spatial_bytes + trajectory_bytes) / point_bytes,
        })
    return out
