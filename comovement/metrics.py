"""Cost, balance and correctness measures, each one DataFrame."""

from __future__ import annotations

import time
from collections.abc import Callable
from typing import TYPE_CHECKING

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .operators import blocks, pointjoin
from .operators.general import compare as compare_bags
from .params import JoinParams
from .plans.partitioning import Slabs, expand
from .plans.quadtree import Quadtree

if TYPE_CHECKING:
    from .engine import SubtrajectoryJoin


def timed(make: Callable[[], DataFrame]) -> tuple[float, int]:
    """(seconds, rows) of making a DataFrame and producing all its columns."""
    start = time.perf_counter()
    df = make()
    rows = df.select(F.xxhash64(*df.columns).alias("h")).agg(F.count("*"), F.max("h")).first()[0]
    return time.perf_counter() - start, rows


def slab_sizes(pts: DataFrame, slabs: Slabs, eps_t_us: int = 0) -> DataFrame:
    """n and n_expanded of every slab, empty ones included."""
    spark = pts.sparkSession
    every = spark.range(slabs.count).select(F.col("id").cast("int").alias("slab"))
    sizes = expand(pts, slabs, eps_t_us).groupBy("slab").agg(F.count_if("is_home").alias("n"), F.count("*").alias("n_expanded"))
    zero = F.lit(0).cast("long")
    return every.join(sizes, "slab", "left").select("slab", F.coalesce("n", zero).alias("n"), F.coalesce("n_expanded", zero).alias("n_expanded"))


def balance(sizes: DataFrame, column: str = "n") -> DataFrame:
    """Standard deviation, mean and extremes of the slabs' input sizes."""
    return sizes.agg(F.round(F.stddev_pop(column), 6).alias("sigma"), F.round(F.avg(column), 6).alias("mean"), F.min(column).alias("least"), F.max(column).alias("most"))


def replication(pts: DataFrame, slabs: Slabs, eps_t_us: int) -> DataFrame:
    """Rows before and after the expansion by eps_t, and their ratio."""
    n = expand(pts, slabs, eps_t_us).agg(F.count_if("is_home").alias("n"), F.count("*").alias("n_expanded"))
    return n.select("n", "n_expanded", F.round(F.col("n_expanded") / F.col("n"), 6).alias("factor"))


POINT_BYTES, CELL_BYTES, SPATIAL_BYTES, TRAJECTORY_BYTES = 48, 48, 12, 16
"""Bytes of a point; of a cell of the tree; of an entry of the spatial index (cell, place in time order) and of the
trajectory index (trajectory, number)."""


def index_size(pts: DataFrame, tree: Quadtree, eps_sp: float) -> DataFrame:
    """Entries and bytes of the spatial index (a point for each cell it is near, and the cells) and of the trajectory
    index (a number for each point), and their share of the points' own bytes."""
    n = pts.agg(F.sum(F.size(tree.touched_cells(F.col("x"), F.col("y"), eps_sp)).cast("long")).alias("spatial_rows"), F.count("*").alias("trajectory_rows"))
    spatial = F.col("spatial_rows") * SPATIAL_BYTES + F.lit(len(tree.leaves) * CELL_BYTES)
    sized = n.select("spatial_rows", "trajectory_rows", spatial.alias("spatial_bytes"), (F.col("trajectory_rows") * TRAJECTORY_BYTES).alias("trajectory_bytes"))
    return sized.withColumn("ratio", F.round((F.col("spatial_bytes") + F.col("trajectory_bytes")) / (F.col("trajectory_rows") * POINT_BYTES), 6))


def selectivities(pts: DataFrame, params: JoinParams) -> DataFrame:
    """Pairs within eps_t (candidates), joining pairs, a = share of pairs in time, b = share of those in space."""
    from .operators.general import band_join

    r = pts.selectExpr("traj r_traj", "t r_t", "x r_x", "y r_y")
    s = pts.selectExpr("traj s_traj", "t s_t", "x s_x", "y s_y")
    near = band_join(r, s, "r_t", "s_t", params.eps_t_us).where("r_traj <> s_traj")
    found = near.agg(F.count("*").alias("candidates"), F.count_if(pointjoin.close(params)).alias("n_jp"))
    n = pts.agg(F.count("*").alias("n"))
    out = found.join(F.broadcast(n))  # one row each
    return out.select("n", "candidates", "n_jp", F.round(F.col("candidates") / (F.col("n") * F.col("n")), 9).alias("a"), F.round(F.col("n_jp") / F.col("candidates"), 9).alias("b"))


def intermediate(pts: DataFrame, params: JoinParams, tree: Quadtree | None = None) -> DataFrame:
    """Joining pairs, breaking points, candidate misses of a self-join, and their ratio to the input; counted in blocks."""
    found = blocks.tally(pts, params, tree).join(F.broadcast(pts.agg(F.count("*").alias("n_in"))))  # one row each
    n = found.select("n_in", "n_jp", (F.col("n_in") - F.col("n_live")).alias("n_bp"), "n_miss")
    return n.withColumn("ratio", F.round((F.col("n_jp") + F.col("n_bp") + F.col("n_miss")) / F.col("n_in"), 6))


def gap(matches: DataFrame, params: JoinParams) -> DataFrame:
    """Matches of the definition whose reference span is under delta_t: a gate on that span would lose them."""
    span = F.col("r_t_to") - F.col("r_t_from")
    return matches.agg(F.count("*").alias("n_matches"), F.count_if(span < params.delta_t_us).alias("n_short_span"))


def gap_in_blocks(join: SubtrajectoryJoin, pts: DataFrame) -> DataFrame:
    """``gap`` of the exact matches of a self-join, counted where they are found."""
    least = join.params.delta_t_us

    def each(frames):
        n = np.zeros(2, np.int64)
        for m in frames:
            n += len(m), np.count_nonzero(m["r_t_to"] - m["r_t_from"] < least)
        yield pd.DataFrame([n], columns=["n_matches", "n_short_span"])

    found = join.reduced(pts, each, "n_matches long, n_short_span long")
    return found.agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in found.columns])


def compare(a: DataFrame, b: DataFrame) -> DataFrame:
    return compare_bags(a, b)


def scan_back(pts: DataFrame) -> DataFrame:
    """One row: the mean number of points, in the order of time, from a point back to the one before on its trajectory.

    The steps of a trajectory add up to the difference of its ends' ranks; ranks come from counts by day and within."""
    day = F.floor(F.col("t") / F.lit(86_400_000_000))
    days = pts.groupBy(day.alias("day")).agg(F.count("*").alias("n"))
    before = days.select("day", F.coalesce(F.sum("n").over(Window.orderBy("day").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    ranked = pts.select("traj", day.alias("day"), F.rank().over(Window.partitionBy(day).orderBy("t")).alias("r")).join(before, "day")
    rank = F.col("before") + F.col("r")
    ends = ranked.groupBy("traj").agg((F.max(rank) - F.min(rank)).alias("steps"), (F.count("*") - 1).alias("k"))
    return ends.agg((F.sum("steps") / F.sum("k")).alias("back"), F.count("*").alias("trajectories"))


def predicted_cost(pts: DataFrame, params: JoinParams, tree: Quadtree) -> DataFrame:
    """Decimal logarithms of the operation counts that the complexity analysis predicts for the sweep, the indexed join
    and the refine step, from measured quantities.

    Sweep: n a ((1 - b) n + 2 b n (L + 2 a n)); indexed, over partitions i of n_i own points and P_i with those within
    the radius: n_i h log2 P_i a P_i ((1 - b) P_i + 2 b P_i (2 log2 T + a T)); refine, for every trajectory:
    T SW dt l. a and b are the selectivities in time and space, L the points to scan back to a trajectory's previous
    one, h the tree's height, T the points of a trajectory, SW and dt those in a window of delta_t and of
    delta_t - 2 eps_t, l the pairs of a point."""
    sel = selectivities(pts, params).select("n", "n_jp", (F.col("candidates") / (F.col("n") * F.col("n"))).alias("a"), (F.col("n_jp") / F.col("candidates")).alias("b"))
    span = lambda us: F.count("*").over(Window.partitionBy("traj").orderBy("t").rangeBetween(0, us))
    windows = pts.select(span(params.delta_t_us).alias("sw"), span(params.inner_window_us).alias("dt")).agg(F.avg("sw").alias("sw"), F.avg("dt").alias("dt"))
    home = pts.groupBy(tree.home_cell(F.col("x"), F.col("y")).alias("cell")).agg(F.count("*").cast("double").alias("own"))
    near = pts.select(F.explode(tree.touched_cells(F.col("x"), F.col("y"), params.eps_sp)).alias("cell")).groupBy("cell").agg(F.count("*").cast("double").alias("p"))
    one = sel.join(F.broadcast(scan_back(pts))).join(F.broadcast(windows))  # one row each
    n, a, b, t = F.col("n").cast("double"), F.col("a"), F.col("b"), F.col("n") / F.col("trajectories")
    p = F.col("p")
    part = F.col("own") * tree.depth * F.log2(p) * a * p * ((1 - b) * p + 2 * b * p * (2 * F.log2(t) + a * t))
    indexed = home.join(near, "cell").join(F.broadcast(one)).agg(F.sum(part).alias("indexed"))
    log = lambda x, name: F.round(F.log10(x), 6).alias(name)
    return one.join(F.broadcast(indexed)).select(
        "n", F.lit(len(tree.leaves)).cast("long").alias("leaves"), F.round("back", 6).alias("scan_back"), F.round("sw", 6).alias("in_window"), F.round("dt", 6).alias("in_inner_window"),
        log(n * a * ((1 - b) * n + 2 * b * n * (F.col("back") + 2 * a * n)), "sweep_log10"), log(F.col("indexed"), "indexed_log10"),
        log(F.col("trajectories") * t * F.col("sw") * F.col("dt") * (F.col("n_jp") / n), "refine_log10"),
    )
