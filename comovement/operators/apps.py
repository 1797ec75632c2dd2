"""Queries on the answer that the join is a building block for.

Those that keep little of many matches have a form for ``SubtrajectoryJoin.reduced`` as well: a function of a block's
frames of matches, the schema of what it gives and, where blocks are to be put together, what is done with it."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .general import top_per
from .refine import SCHEMA


def neighbour_count(pts: DataFrame, jp: DataFrame) -> DataFrame:
    """Number of other trajectories near each point (input of trajectory segmentation)."""
    n = jp.groupBy(F.col("r_traj").alias("traj"), F.col("r_seq").alias("seq")).agg(F.countDistinct("s_traj").alias("n_objects"), F.count("*").alias("n_points"))
    zero = F.lit(0).cast("long")
    return pts.select("traj", "seq").join(n, ["traj", "seq"], "left").select("traj", "seq", F.coalesce("n_objects", zero).alias("n_objects"), F.coalesce("n_points", zero).alias("n_points"))


def rideshare(matches: DataFrame, least_us: int) -> DataFrame:
    """Pairs that share at least least_us in total: trips shared and time together."""
    return matches.groupBy("r_traj", "s_traj").agg(F.count("*").alias("trips"), F.sum("lifespan_us").alias("together_us")).where(F.col("together_us") >= least_us)


def rideshare_each(least_us: int) -> tuple[Callable, str]:
    """``rideshare`` in blocks; a pair's matches stand in one frame, so nothing is left to put together."""

    def each(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for m in frames:
            per = m.groupby(["r_traj", "s_traj"], sort=False)["lifespan_us"].agg(["size", "sum"]).reset_index()
            yield per[per["sum"] >= least_us].set_axis(["r_traj", "s_traj", "trips", "together_us"], axis=1)

    return each, "r_traj long, s_traj long, trips long, together_us long"


def suspicious(matches: DataFrame, least_us: int, repeats: int) -> DataFrame:
    """Pairs that moved together for least_us at a time at least ``repeats`` times."""
    return matches.where(F.col("lifespan_us") >= least_us).groupBy("r_traj", "s_traj").agg(F.count("*").alias("times"), F.max("lifespan_us").alias("longest_us")).where(F.col("times") >= repeats)


def suspicious_each(least_us: int, repeats: int) -> tuple[Callable, str]:
    """``suspicious`` in blocks; a pair's matches stand in one frame, so nothing is left to put together."""

    def each(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for m in frames:
            per = m[m["lifespan_us"] >= least_us].groupby(["r_traj", "s_traj"], sort=False)["lifespan_us"].agg(["size", "max"]).reset_index()
            yield per[per["size"] >= repeats].set_axis(["r_traj", "s_traj", "times", "longest_us"], axis=1)

    return each, "r_traj long, s_traj long, times long, longest_us long"


def groups(mirrored: DataFrame, least_partners: int) -> DataFrame:
    """Trajectories with at least least_partners partners (candidates for flocks and convoys)."""
    return mirrored.groupBy("r_traj").agg(F.countDistinct("s_traj").alias("partners")).where(F.col("partners") >= least_partners).withColumnRenamed("r_traj", "traj")


def top_partners(mirrored: DataFrame, k: int) -> DataFrame:
    """The k partners with which each trajectory spent the longest time in one match."""
    best = mirrored.groupBy("r_traj", "s_traj").agg(F.max("lifespan_us").alias("longest_us"))
    return top_per(best, ["r_traj"], [F.desc("longest_us"), F.col("s_traj")], k)


HELD = 1 << 20
"""Rows that a block gathers before it cuts them to the best."""


def _best(frames: Iterator[pd.DataFrame], cut: Callable[[pd.DataFrame], pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """cut() of all frames of a block, a part at a time."""
    held: list[pd.DataFrame] = []
    kept = 0
    for m in frames:
        held.append(m)
        if sum(map(len, held)) > HELD + 2 * kept:
            held = [cut(pd.concat(held))]
            kept = len(held[0])
    if held:
        yield cut(pd.concat(held))


def top_partners_each(k: int) -> tuple[Callable, str]:
    """``top_partners`` of undirected matches in blocks: each trajectory's best of a block, for ``top_of_blocks``."""

    def both(m: pd.DataFrame) -> pd.DataFrame:
        per = m.groupby(["r_traj", "s_traj"], sort=False)["lifespan_us"].max()
        r, s = (per.index.get_level_values(c).to_numpy() for c in ("r_traj", "s_traj"))
        return pd.DataFrame({"r_traj": np.append(r, s), "s_traj": np.append(s, r), "longest_us": np.tile(per.to_numpy(), 2)})

    def cut(best: pd.DataFrame) -> pd.DataFrame:
        r = best["r_traj"].to_numpy()
        order = np.lexsort((best["s_traj"], -best["longest_us"], r))
        r = r[order]
        first = np.flatnonzero(np.append(True, r[1:] != r[:-1]))
        rank = np.arange(len(r)) - np.repeat(first, np.diff(np.append(first, len(r))))
        return best.iloc[order[rank < k]]

    return lambda frames: _best(map(both, frames), cut), "r_traj long, s_traj long, longest_us long"


def top_of_blocks(best: DataFrame, k: int) -> DataFrame:
    """The k best partners of each trajectory among those of its blocks; a pair of trajectories is in one block."""
    return top_per(best, ["r_traj"], [F.desc("longest_us"), F.col("s_traj")], k)


def longest_each(k: int) -> tuple[Callable, str]:
    """The k longest matches of a block, for ``longest``."""
    by, down = ["lifespan_us", "r_traj", "s_traj", "r_from"], [False, True, True, True]
    return lambda frames: _best(frames, lambda m: m.sort_values(by, ascending=down).head(k)), SCHEMA


def longest(matches: DataFrame, k: int) -> DataFrame:
    """The k longest matches."""
    return matches.orderBy(F.desc("lifespan_us"), "r_traj", "s_traj", "r_from").limit(k)


def shared_segments(matches: DataFrame, pts: DataFrame, side: float) -> DataFrame:
    """Edges of a movement network: steps between grid cells along matched pieces, with the pairs using them."""
    piece = matches.selectExpr("r_traj traj", "r_from seq_from", "r_to seq_to", "s_traj partner")
    steps = pts.where("next_x is not null").join(piece, "traj").where("seq >= seq_from and seq < seq_to")
    cell = lambda c: F.floor(F.col(c) / F.lit(side)).cast("long")
    edge = steps.select("traj", "partner", cell("x").alias("from_x"), cell("y").alias("from_y"), cell("next_x").alias("to_x"), cell("next_y").alias("to_y"))
    ends = ["from_x", "from_y", "to_x", "to_y"]
    # pairs of one trajectory are told apart where the join by trajectory has them, so steps are not shuffled
    return edge.groupBy("traj", *ends).agg(F.countDistinct("partner").alias("n")).groupBy(*ends).agg(F.sum("n").alias("pairs"))


def _whole_cells(v: np.ndarray, side: float) -> np.ndarray:
    """floor(v / side) as a long, at its ends beyond them."""
    f, end = np.floor(v / side), 2.0**63
    return np.where(f >= end, np.iinfo(np.int64).max, np.where(f >= end, 0.0, np.maximum(f, -end)).astype(np.int64))


def shared_segments_each(side: float) -> tuple[Callable, str]:
    """``shared_segments`` in blocks, with the sides of a block (``reduced`` with sides=True): the pairs of its trajectories on each
    edge, for ``segments_of_blocks``. A pair's matches stand in one frame, so its edges are told apart there."""

    def steps(own) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Edges of a side, the edge from each point to the next (the last one's is not used), and its points as one number."""
        (xs, x), (ys, y) = (np.unique(_whole_cells(v, side), return_inverse=True) for v in (own.x, own.y))
        cells, cell = np.unique(x * len(ys) + y, return_inverse=True)
        edges, at = np.unique(cell * len(cells) + np.roll(cell, -1), return_inverse=True)
        ends = [cells[k] for k in np.divmod(edges, len(cells))]
        return np.column_stack([v for end in ends for v in (xs[end // len(ys)], ys[end % len(ys)])]), at, own.place(own.code, own.seq)

    def each(frames: Iterator[pd.DataFrame], a, b) -> Iterator[pd.DataFrame]:
        sides = [(own, *steps(own)) for own in ((a,) if a is b else (a, b))]
        n = [np.zeros(len(edges), np.int64) for _, edges, _, _ in sides]
        for m in frames:
            r, first, last = (m[c].to_numpy() for c in ("r_traj", "r_from", "r_to"))
            pair = np.unique(np.column_stack([r, m["s_traj"].to_numpy()]), axis=0, return_inverse=True)[1].ravel()
            for k, (own, edges, at, place) in enumerate(sides):
                code = np.searchsorted(own.names, r)
                ok = own.names[np.minimum(code, len(own.names) - 1)] == r
                # numbers of a piece are consecutive, so are its rows
                start, size = np.searchsorted(place, own.place(code[ok], first[ok])), (last - first)[ok]
                row = np.repeat(start - np.append(0, np.cumsum(size)[:-1]), size) + np.arange(size.sum())
                used = np.unique(np.repeat(pair[ok], size) * len(edges) + at[row])
                n[k] += np.bincount(used % len(edges), minlength=len(edges))
        for (_, edges, _, _), pairs in zip(sides, n):
            found = pd.DataFrame(edges[pairs > 0], columns=["from_x", "from_y", "to_x", "to_y"])
            yield found.assign(n=pairs[pairs > 0])

    return each, "from_x long, from_y long, to_x long, to_y long, n long"


def segments_of_blocks(found: DataFrame) -> DataFrame:
    """The movement network of what blocks found; a pair of trajectories is in one block."""
    return found.groupBy("from_x", "from_y", "to_x", "to_y").agg(F.sum("n").alias("pairs"))
