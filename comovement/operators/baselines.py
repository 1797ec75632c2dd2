"""Answers that the join is compared with: fixed duration, whole trajectories, pairs alone, time-warped distance."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..params import JoinParams
from .general import overlap_join
from .refine import grouped


def fixed_duration(jp: DataFrame, pts: DataFrame, params: JoinParams) -> DataFrame:
    """Windows of exactly delta_t over the reference in which the partner's run is present at every point:
    r_traj, s_traj, r_from, r_to for each start."""
    following = pts.select(F.col("traj").alias("r_traj"), F.col("seq").alias("r_seq"), "next_t")
    edges = grouped(jp).join(following, ["r_traj", "r_seq"])
    points = edges.select("r_traj", "s_traj", "x_run", "p_run", "r_seq", "r_t", "next_t").distinct()
    w = Window.partitionBy("r_traj", "s_traj", "x_run", "p_run")
    after = F.max(F.struct("r_seq", "next_t")).over(w)["next_t"]
    stop = F.max("r_seq").over(w.orderBy("r_t").rangeBetween(0, params.delta_t_us))
    windows = points.withColumn("after", after).withColumn("r_to", stop).withColumn("last_t", F.max("r_t").over(w))
    whole = (F.col("last_t") >= F.col("r_t") + params.delta_t_us) & (F.col("after").isNull() | (F.col("after") > F.col("r_t") + params.delta_t_us))
    return windows.where(whole & (F.col("r_to") > F.col("r_seq"))).select("r_traj", "s_traj", F.col("r_seq").alias("r_from"), "r_to").distinct()


def whole_trajectory(matches: DataFrame, pts: DataFrame) -> DataFrame:
    """Matches that span both trajectories from end to end."""
    n = pts.groupBy("traj").agg(F.count("*").alias("n"))
    r, s = n.selectExpr("traj r_traj", "n r_len"), n.selectExpr("traj s_traj", "n s_len")
    return matches.join(r, "r_traj").join(s, "s_traj").where("n_r = r_len and n_s = s_len").drop("r_len", "s_len")


def jp_only_runs(jp: DataFrame, params: JoinParams) -> DataFrame:
    """What one gets from joining pairs alone: one pass of reference runs, blind to breaks of the partner.
    Wrong on purpose; compare it with the exact answer."""
    w = Window.partitionBy("r_traj", "s_traj")
    run = jp.withColumn("g", F.col("r_seq") - F.dense_rank().over(w.orderBy("r_seq")))
    m = run.groupBy("r_traj", "s_traj", "g").agg(
        F.min("r_seq").alias("r_from"), F.max("r_seq").alias("r_to"), F.min("s_seq").alias("s_from"), F.max("s_seq").alias("s_to"),
        (F.least(F.max("r_t"), F.max("s_t")) - F.greatest(F.min("r_t"), F.min("s_t"))).alias("lifespan_us"),
    )
    long_enough = (F.col("r_to") > F.col("r_from")) & (F.col("s_to") > F.col("s_from")) & (F.col("lifespan_us") >= params.lifespan_floor_us)
    return m.where(long_enough).select("r_traj", "s_traj", "r_from", "r_to", "s_from", "s_to")


def warping_distance(a: np.ndarray, b: np.ndarray) -> float:
    """Dynamic time warping distance of two point sequences, a diagonal of the table at a time."""
    cost = np.sqrt(((a[:, None] - b[None]) ** 2).sum(axis=2))
    n, m = cost.shape
    table = np.full((n + 1, m + 1), np.inf)
    table[0, 0] = 0.0
    for d in range(n + m - 1):
        i = np.arange(max(0, d - m + 1), min(n, d + 1))
        j = d - i
        table[i + 1, j + 1] = cost[i, j] + np.minimum(np.minimum(table[i, j + 1], table[i + 1, j]), table[i, j])
    return float(table[n, m])


def warped_join(pts: DataFrame, most: float, width_us: int) -> DataFrame:
    """Pairs of whole trajectories (r < s) with warping distance at most ``most``; only trajectories whose
    lifespans overlap and whose boxes come within ``most`` are compared."""
    t = pts.groupBy("traj").agg(
        F.min("t").alias("lo"), F.max("t").alias("hi"), F.min("x").alias("x0"), F.max("x").alias("x1"), F.min("y").alias("y0"), F.max("y").alias("y1"),
        F.array_sort(F.collect_list(F.struct("t", "pid", "x", "y"))).alias("p"),
    )
    r, s = t.select(*[F.col(c).alias(f"r_{c}") for c in t.columns]), t.select(*[F.col(c).alias(f"s_{c}") for c in t.columns])
    near = overlap_join(r, s, ("r_lo", "r_hi"), ("s_lo", "s_hi"), width_us).where("r_traj < s_traj")
    near = near.where(F.expr(f"greatest(r_x0, s_x0) - least(r_x1, s_x1) <= {most} and greatest(r_y0, s_y0) - least(r_y1, s_y1) <= {most}"))

    def run(batches):
        for pdf in batches:
            xy = lambda p: np.array([(q["x"], q["y"]) for q in p], float).reshape(-1, 2)
            d = [warping_distance(xy(a), xy(b)) for a, b in zip(pdf["r_p"], pdf["s_p"])]
            out = pd.DataFrame({"r_traj": pdf["r_traj"], "s_traj": pdf["s_traj"], "distance": d})
            yield out[out["distance"] <= most]

    return near.select("r_traj", "s_traj", "r_p", "s_p").mapInPandas(run, "r_traj long, s_traj long, distance double")
