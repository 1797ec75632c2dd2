"""The definitions themselves: matching and maximality tests, and a brute force for small inputs."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..params import JoinParams
from ..sources.tables import MATCH_COLUMNS
from .general import runs


def is_matching(jp: DataFrame, pieces: DataFrame, params: JoinParams) -> DataFrame:
    """pieces (MATCH columns) with ``matching``: every point covered from the other side, and the lifespan long enough."""
    e = jp.select("r_traj", "s_traj", "r_seq", "s_seq")
    inside = pieces.join(e, ["r_traj", "s_traj"]).where("r_seq between r_from and r_to and s_seq between s_from and s_to")
    covered = inside.groupBy("r_traj", "s_traj", "r_from", "r_to", "s_from", "s_to").agg(F.countDistinct("r_seq").alias("c_r"), F.countDistinct("s_seq").alias("c_s"))
    out = pieces.join(covered, ["r_traj", "s_traj", "r_from", "r_to", "s_from", "s_to"], "left")
    full = (F.col("c_r") == F.col("r_to") - F.col("r_from") + 1) & (F.col("c_s") == F.col("s_to") - F.col("s_from") + 1)
    return out.withColumn("matching", F.coalesce(full, F.lit(False)) & (F.col("lifespan_us") >= params.lifespan_floor_us)).drop("c_r", "c_s")


def is_maximal(matches: DataFrame) -> DataFrame:
    """Matches that no other match contains, by an anti-join on trajectory pairs."""
    other = matches.select(*[F.col(c).alias(f"o_{c}") for c in ("r_traj", "s_traj", "r_from", "r_to", "s_from", "s_to")])
    inside = (F.col("r_traj") == F.col("o_r_traj")) & (F.col("s_traj") == F.col("o_s_traj")) & F.expr("o_r_from <= r_from and o_r_to >= r_to and o_s_from <= s_from and o_s_to >= s_to")
    return matches.join(other, inside & F.expr("not (o_r_from = r_from and o_r_to = r_to and o_s_from = s_from and o_s_to = s_to)"), "left_anti")


PIECE = 1 << 20
"""Rows that a test of frames looks at in one go."""


def _spread(first: np.ndarray, last: np.ndarray):
    """For each piece of rows: rows (repeated) and the places first to last (exclusive) of each."""
    n = np.maximum(last - first, 0)
    upto, start = np.cumsum(n), 0
    while start < len(n):
        done = int(upto[start - 1]) if start else 0
        stop = max(start + 1, int(np.searchsorted(upto, done + PIECE, "right")))
        row = np.repeat(np.arange(start, stop), n[start:stop])
        yield row, np.arange(len(row)) - np.repeat(upto[start:stop] - n[start:stop] - done, n[start:stop]) + first[row]
        start = stop


def _pairs_of(*frames: pd.DataFrame) -> list[np.ndarray]:
    """A number for each row's pair of trajectories, the same in all frames."""
    r, s = (np.unique(np.concatenate([f[c] for f in frames]), return_inverse=True)[1] for c in ("r_traj", "s_traj"))
    pair = np.unique(r * (int(s.max(initial=0)) + 1) + s, return_inverse=True)[1]
    return np.split(pair, np.cumsum([len(f) for f in frames])[:-1])


def matching_rows(edges: pd.DataFrame, m: pd.DataFrame, params: JoinParams) -> np.ndarray:
    """``is_matching`` of a frame: edges (r_traj, s_traj, r_seq, s_seq) are all joining pairs of the pairs of trajectories of m."""
    pair_m, pair_e = _pairs_of(m, edges)
    order = np.lexsort((edges["r_seq"], pair_e))
    pair_e, q, v = pair_e[order], edges["r_seq"].to_numpy()[order], edges["s_seq"].to_numpy()[order]
    numbers = np.unique(q)
    step = len(numbers) + 1  # (pair, number) as one, by the number's rank
    key = pair_e * step + np.searchsorted(numbers, q)
    first = np.searchsorted(key, pair_m * step + np.searchsorted(numbers, m["r_from"]))
    last = np.searchsorted(key, pair_m * step + np.searchsorted(numbers, m["r_to"], "right"))
    lo, hi = m["s_from"].to_numpy(), m["s_to"].to_numpy()
    covered = np.zeros((2, len(m)), np.int64)
    for row, at in _spread(first, last):
        inside = (v[at] >= lo[row]) & (v[at] <= hi[row])
        row, at = row[inside], at[inside]
        for side, number in enumerate((q[at], v[at])):
            by = np.lexsort((number, row))
            new = np.append(True, (np.diff(row[by]) != 0) | (np.diff(number[by]) != 0))[: len(by)]
            covered[side] += np.bincount(row[by][new], minlength=len(m))
    full = (covered[0] == m["r_to"] - m["r_from"] + 1) & (covered[1] == hi - lo + 1)
    return (full & (m["lifespan_us"] >= params.lifespan_floor_us)).to_numpy()


def maximal_rows(m: pd.DataFrame) -> np.ndarray:
    """``is_maximal`` of a frame with all matches of its pairs of trajectories."""
    (pair,) = _pairs_of(m)
    order = np.argsort(pair, kind="stable")
    ends = [m[c].to_numpy()[order] for c in ("r_from", "s_from", "r_to", "s_to")]
    first, last = (np.searchsorted(pair[order], pair[order], side) for side in ("left", "right"))
    inside = np.zeros(len(m), bool)
    for row, at in _spread(first, last):
        holds = (ends[0][at] <= ends[0][row]) & (ends[1][at] <= ends[1][row]) & (ends[2][at] >= ends[2][row]) & (ends[3][at] >= ends[3][row])
        same = np.logical_and.reduce([e[at] == e[row] for e in ends])
        inside[row[holds & ~same]] = True
    out = np.empty(len(m), bool)
    out[order] = ~inside
    return out


def brute_force(jp: DataFrame, pts: DataFrame, params: JoinParams) -> DataFrame:
    """All maximal matches by enumerating pieces of runs; exponential in nothing but quartic in run length."""

    def pieces(side: str) -> DataFrame:
        r = runs(jp.select("r_traj", "s_traj", f"{side}_seq").distinct(), ["r_traj", "s_traj"], f"{side}_seq")
        cut = r.withColumn("a", F.explode(F.sequence("seq_from", "seq_to"))).withColumn("b", F.explode(F.sequence("a", "seq_to")))
        cut = cut.where(F.col("b") - F.col("a") + 1 >= params.min_points)
        at = lambda name: pts.select(F.col("traj").alias(f"{side}_traj"), F.col("seq").alias(name), F.col("t").alias(f"t_{name}"))
        cut = cut.join(at("a"), [f"{side}_traj", "a"]).join(at("b"), [f"{side}_traj", "b"])
        return cut.select("r_traj", "s_traj", F.col("a").alias(f"{side}_from"), F.col("b").alias(f"{side}_to"), F.col("t_a").alias(f"{side}_t_from"), F.col("t_b").alias(f"{side}_t_to"), (F.col("b") - F.col("a") + 1).alias(f"n_{side}"))

    both = pieces("r").join(pieces("s"), ["r_traj", "s_traj"]).withColumn("lifespan_us", F.least("r_t_to", "s_t_to") - F.greatest("r_t_from", "s_t_from"))
    return is_maximal(is_matching(jp, both.select(*MATCH_COLUMNS), params).where("matching").select(*MATCH_COLUMNS))
