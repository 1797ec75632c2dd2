"""From joining pairs to maximal matches.

Exact: inside a pair of trajectories, joining pairs are the edges of a graph on sequence numbers.
Every round splits a component where its reference positions or its other positions are not
consecutive; components that no longer split are the maximal mutually covering pairs, and the
duration and length tests may follow. The number of rounds depends on the data, so after one shuffle
and one sort an Arrow kernel runs them over many trajectory pairs at once; ``by_rounds`` is the same
as window functions.

Windowed: reads joining pairs, breaking points and candidate misses with their kind, by reference
trajectory. A miss ends a run of the other trajectory, a breaking point ends every run it stands in.

Kernels stream: a frame is cut where nothing reaches across (a gap of the reference, a pair), so a task
holds a batch and one run, not a trajectory pair or more.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..params import JoinParams
from ..sources.scratch import written
from ..sources.tables import MATCH_COLUMNS

SCHEMA = ", ".join(f"{c} long" for c in MATCH_COLUMNS)


def _round(edges: DataFrame) -> DataFrame:
    key = ["r_traj", "s_traj", "c_r", "c_s"]
    w = Window.partitionBy(*key)
    runs = edges.withColumn("g_r", F.col("r_seq") - F.dense_rank().over(w.orderBy("r_seq"))).withColumn("g_s", F.col("s_seq") - F.dense_rank().over(w.orderBy("s_seq")))
    firsts = runs.withColumn("n_r", F.min("r_seq").over(Window.partitionBy(*key, "g_r"))).withColumn("n_s", F.min("s_seq").over(Window.partitionBy(*key, "g_s")))
    return firsts.select("r_traj", "s_traj", "r_seq", "s_seq", "r_t", "s_t", F.col("n_r").alias("c_r"), F.col("n_s").alias("c_s"))


def _pruned(edges: DataFrame, params: JoinParams) -> DataFrame:
    """Drops components that can no longer qualify: a part's lifespan and length are at most its own."""
    w = Window.partitionBy("r_traj", "s_traj", "c_r", "c_s")
    out = edges
    for side in ("r", "s"):
        span = F.max(f"{side}_t").over(w) - F.min(f"{side}_t").over(w)
        length = F.max(f"{side}_seq").over(w) - F.min(f"{side}_seq").over(w) + 1
        out = out.withColumn(f"_{side}", (span >= params.lifespan_floor_us) & (length >= params.min_points))
    return out.where("_r and _s").drop("_r", "_s")


def _summed(edges: DataFrame, params: JoinParams) -> DataFrame:
    agg = [f(f"{side}_{what}").alias(f"{side}_{how}_{what}") for side in ("r", "s") for what in ("seq", "t") for how, f in (("min", F.min), ("max", F.max))]
    m = edges.groupBy("r_traj", "s_traj", "c_r", "c_s").agg(*agg)
    m = m.select(
        "r_traj", F.col("r_min_seq").alias("r_from"), F.col("r_max_seq").alias("r_to"), F.col("r_min_t").alias("r_t_from"), F.col("r_max_t").alias("r_t_to"),
        "s_traj", F.col("s_min_seq").alias("s_from"), F.col("s_max_seq").alias("s_to"), F.col("s_min_t").alias("s_t_from"), F.col("s_max_t").alias("s_t_to"),
        (F.least("r_max_t", "s_max_t") - F.greatest("r_min_t", "s_min_t")).alias("lifespan_us"),
        (F.col("r_max_seq") - F.col("r_min_seq") + 1).alias("n_r"), (F.col("s_max_seq") - F.col("s_min_seq") + 1).alias("n_s"),
    )
    return _tested(m, params)


def _tested(matches: DataFrame, params: JoinParams) -> DataFrame:
    return matches.where((F.col("lifespan_us") >= params.lifespan_floor_us) & (F.col("n_r") >= params.min_points) & (F.col("n_s") >= params.min_points))


def whole_units(batches, columns: list[str], starts) -> Iterator[np.ndarray]:
    """Frames (rows, columns) of whole units from sorted batches; ``starts`` marks the first row of each unit."""
    rest = np.empty((0, len(columns)), np.int64)
    for pdf in batches:
        e = np.concatenate([rest, pdf[columns].to_numpy(np.int64)])
        if len(e):
            last = int(np.flatnonzero(starts(e))[-1])
            if last:
                yield e[:last]
            rest = e[last:]
    if len(rest):
        yield rest


def _changes(*columns: np.ndarray) -> np.ndarray:
    """Whether a row differs from the one before; the first does."""
    new = np.zeros(len(columns[0]), bool)
    new[:1] = True
    for c in columns:
        new[1:] |= c[1:] != c[:-1]
    return new


def components_of(r: np.ndarray, s: np.ndarray, comp: np.ndarray | None = None) -> np.ndarray:
    """Stable component number of each edge (r, s), starting from ``comp``: rounds until nothing splits."""
    comp = np.zeros(len(r), np.int64) if comp is None else comp

    def runs(v: np.ndarray) -> np.ndarray:
        order = np.lexsort((v, comp))
        c, x = comp[order], v[order]
        out = np.empty(len(v), np.int64)
        out[order] = np.cumsum(_changes(c) | np.append(False, x[1:] > x[:-1] + 1))
        return out

    while len(r):
        before = len(np.unique(comp))
        values, comp = np.unique(runs(r) * (len(r) + 1) + runs(s), return_inverse=True)
        if len(values) == before:
            break
    return comp


_EDGE = ["r_traj", "s_traj", "r_seq", "s_seq", "r_t", "s_t"]


def _pieces(e: np.ndarray, piece: np.ndarray, floor: int, least: int) -> pd.DataFrame:
    """MATCH rows of edges (columns as in _EDGE) by piece, which pass the duration and length tests."""
    order = np.argsort(piece, kind="stable")
    e, starts = e[order], np.flatnonzero(_changes(piece[order]))
    low, high = np.minimum.reduceat(e, starts, axis=0), np.maximum.reduceat(e, starts, axis=0)
    m = pd.DataFrame({"r_traj": low[:, 0], "s_traj": low[:, 1]})
    for k, side in ((2, "r"), (3, "s")):
        m[f"{side}_from"], m[f"{side}_to"], m[f"{side}_t_from"], m[f"{side}_t_to"] = low[:, k], high[:, k], low[:, k + 2], high[:, k + 2]
        m[f"n_{side}"] = m[f"{side}_to"] - m[f"{side}_from"] + 1
    m["lifespan_us"] = np.minimum(m["r_t_to"], m["s_t_to"]) - np.maximum(m["r_t_from"], m["s_t_from"])
    return m.loc[(m["lifespan_us"] >= floor) & (m["n_r"] >= least) & (m["n_s"] >= least), list(MATCH_COLUMNS)]


def kernel(params: JoinParams):
    """Edges sorted by trajectory pair and reference to matches; a unit is a run of the reference."""
    floor, least = params.lifespan_floor_us, params.min_points

    def starts(e: np.ndarray) -> np.ndarray:
        return _changes(e[:, 0], e[:, 1]) | np.append(False, e[1:, 2] > e[:-1, 2] + 1)

    def run(batches):
        for e in whole_units(batches, _EDGE, starts):
            new = starts(e)
            first = np.flatnonzero(new)
            last = np.append(first[1:], len(e)) - 1
            # a part is no longer than its run
            open_ = (e[last, 4] - e[first, 4] >= floor) & (e[last, 2] - e[first, 2] + 1 >= least)
            unit = np.cumsum(new) - 1
            keep = open_[unit]
            e, unit = e[keep], unit[keep]
            if len(e):
                yield _pieces(e, components_of(e[:, 2], e[:, 3], unit), floor, least)

    return run


def maximal_matches(jp: DataFrame, params: JoinParams) -> DataFrame:
    """Exact maximal matches: one shuffle by trajectory pair, one sort, one kernel."""
    sorted_ = jp.select(*_EDGE).repartition("r_traj", "s_traj").sortWithinPartitions("r_traj", "s_traj", "r_seq", "s_seq")
    return sorted_.mapInPandas(kernel(params), SCHEMA)


def by_rounds(jp: DataFrame, params: JoinParams, rounds: int = 3, prune: bool = True) -> DataFrame:
    """The exact refine with ``rounds`` rounds as window functions; components that would still split go to
    the kernel on their own (components are independent). The rounds are written once and read twice."""
    # dealt once: every window below is of parts of a trajectory pair
    edges = jp.repartition("r_traj", "s_traj").select(*_EDGE, F.lit(0).cast("long").alias("c_r"), F.lit(0).cast("long").alias("c_s"))
    for k in range(rounds):
        edges = _round(edges)
        if prune and k == 0:
            edges = _pruned(edges, params)
    w = Window.partitionBy("r_traj", "s_traj", "c_r", "c_s")
    again = edges.withColumn("g_r", F.col("r_seq") - F.dense_rank().over(w.orderBy("r_seq"))).withColumn("g_s", F.col("s_seq") - F.dense_rank().over(w.orderBy("s_seq")))
    whole = (F.min("g_r").over(w) == F.max("g_r").over(w)) & (F.min("g_s").over(w) == F.max("g_s").over(w))
    marked = written(again.withColumn("whole", whole).drop("g_r", "g_s"), "rounds")
    done = _summed(marked.where("whole"), params)
    return done.select(*MATCH_COLUMNS).unionByName(maximal_matches(marked.where("not whole"), params))


def mirrored(matches: DataFrame) -> DataFrame:
    """Both directions of undirected matches."""
    swap = {c: ("s" + c[1:] if c.startswith("r_") else "r" + c[1:] if c.startswith("s_") else {"n_r": "n_s", "n_s": "n_r"}.get(c, c)) for c in MATCH_COLUMNS}
    both = F.array(F.struct(*[F.col(c) for c in MATCH_COLUMNS]), F.struct(*[F.col(swap[c]).alias(c) for c in MATCH_COLUMNS]))
    return matches.select(F.explode(both).alias("m")).select("m.*")  # the matches are found once


def grouped(jp: DataFrame) -> DataFrame:
    """Joining pairs with the number of x's run (a miss of x is a hole between runs) and of p's run in it."""
    x = Window.partitionBy("r_traj", "s_traj").orderBy("s_seq")
    runs = jp.withColumn("x_run", F.col("s_seq") - F.dense_rank().over(x))
    p = Window.partitionBy("r_traj", "s_traj", "x_run").orderBy("r_seq")
    return runs.withColumn("p_run", F.col("r_seq") - F.dense_rank().over(p))


BREAK, MISS, PAIR = 0, 1, 2
NONE = 2**63 - 1
"""Stands for "no point" in the rows of the windowed refine: later than any time, above any number."""
_TAGGED = ["kind", "r_traj", "s_traj", "r_seq", "s_seq", "r_t", "s_t", "r_next_t"]


def tagged_pairs(jp: DataFrame, bp: DataFrame, misses: DataFrame) -> DataFrame:
    """What the refine step reads, by reference trajectory: breaking points (no partner), then for each partner
    its pairs and the misses beside them. jp carries r_next_t, the time of the reference's next point."""
    none = F.lit(NONE)
    breaks = bp.select(F.lit(BREAK).alias("kind"), F.col("traj").alias("r_traj"), F.lit(-NONE).alias("s_traj"), F.col("seq").alias("r_seq"), none.alias("s_seq"), F.col("t").alias("r_t"), none.alias("s_t"), none.alias("r_next_t"))
    beside = misses.select(F.lit(MISS).alias("kind"), "r_traj", "s_traj", none.alias("r_seq"), "s_seq", none.alias("r_t"), none.alias("s_t"), none.alias("r_next_t"))
    pairs = jp.select(F.lit(PAIR).alias("kind"), "r_traj", "s_traj", "r_seq", "s_seq", "r_t", "s_t", F.coalesce("r_next_t", none).alias("r_next_t"))
    return breaks.unionByName(beside).unionByName(pairs)


def x_runs(e: np.ndarray) -> np.ndarray:
    """Number of the partner's run of each tagged row: a miss ends one (rows sorted by pair, then partner's number)."""
    return np.cumsum(_changes(e[:, 1], e[:, 2])) + np.cumsum(e[:, 0] == MISS)


def p_runs(run: np.ndarray, seq: np.ndarray, breaks_before: np.ndarray) -> np.ndarray:
    """Number of the reference's run within each partner's run: a breaking point or any other gap ends one."""
    return np.cumsum(_changes(run, breaks_before) | np.append(False, seq[1:] > seq[:-1] + 1)) - 1


def inner_windows(run: np.ndarray, t: np.ndarray, after: np.ndarray, reach: int) -> np.ndarray:
    """For each position the last one of its run within ``reach``; -1 where a later point of the reference,
    outside the run (its time is ``after``), lies within reach too."""
    times = np.unique(t)
    step = len(times) + 1  # (run, time) as one number, by the time's rank
    stop = np.searchsorted(run * step + np.searchsorted(times, t), run * step + np.searchsorted(times, t + reach, "right") - 1, "right") - 1
    return np.where((after == NONE) | (after > t + reach), stop, -1)


def stitched(stop: np.ndarray, run: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(whether a position lies in some valid window, number of its stretch of overlapping windows)."""
    covered = np.maximum.accumulate(stop) >= np.arange(len(stop))
    return covered, np.cumsum(covered & (_changes(run) | np.append(True, ~covered[:-1])))


def windowed_kernel(params: JoinParams, gate: str):
    """Tagged rows sorted by reference, partner (breaks first) and partner's number to windowed matches."""
    reach, floor, delta = params.inner_window_us, params.lifespan_floor_us, params.delta_t_us

    def run(batches):
        held = np.empty((0, 2), np.int64)  # breaks (trajectory, number) of the last trajectory seen
        for e in whole_units(batches, _TAGGED, lambda e: _changes(e[:, 1], e[:, 2])):
            breaks = np.concatenate([held, e[e[:, 0] == BREAK][:, [1, 3]]])
            held = breaks[breaks[:, 0] == e[-1, 1]]
            x = x_runs(e)
            pair = e[:, 0] == PAIR
            if not pair.any():
                continue
            order = np.lexsort((e[pair, 4], e[pair, 3], x[pair]))
            x, e = x[pair][order], e[pair][order]
            names = np.unique(e[:, 1])
            breaks = breaks[np.isin(breaks[:, 0], names)]
            number = lambda traj, seq: np.searchsorted(names, traj) * (1 << 40) + seq  # noqa: B023, E731
            before = np.searchsorted(np.sort(number(breaks[:, 0], breaks[:, 1])), number(e[:, 1], e[:, 3]))
            p = p_runs(x, e[:, 3], before)
            first = np.flatnonzero(_changes(p))
            last = np.append(first[1:], len(e)) - 1
            low, high = np.minimum.reduceat(e, first, axis=0), np.maximum.reduceat(e, first, axis=0)
            if gate == "span":
                open_ = high[:, 5] - low[:, 5] >= delta
            else:
                open_ = np.minimum(high[:, 5], high[:, 6]) - np.maximum(low[:, 5], low[:, 6]) >= floor
            after = e[last, 7]
            keep = open_[p]
            e, p, after = e[keep], p[keep], after[p[keep]]
            if not len(e):
                continue
            new = _changes(p, e[:, 3])  # rows of one position stand together
            at = np.flatnonzero(new)
            covered, stretch = stitched(inner_windows(p[at], e[at, 5], after[at], reach), p[at])
            position = np.cumsum(new) - 1
            inside = covered[position]
            if inside.any():
                yield _pieces(e[inside][:, 1:7], stretch[position[inside]], -(2**62), params.min_points)

    return run


def windowed(jp: DataFrame, bp: DataFrame, misses: DataFrame, params: JoinParams, gate: str = "span") -> DataFrame:
    """Windowed refine of directed pairs, breaking points and misses (r_traj, s_traj, s_seq): a reference window
    slides over each run, a start is valid if all reference points within the inner window belong to the run,
    valid windows are stitched. One shuffle by reference trajectory, one sort, one kernel.

    gate: 'span' asks the run's reference span >= delta_t, 'lifespan' its common lifespan >= delta_t - 2 eps_t."""
    rows = tagged_pairs(jp, bp, misses).select(*_TAGGED).repartition("r_traj").sortWithinPartitions("r_traj", "s_traj", "s_seq")
    return rows.mapInPandas(windowed_kernel(params, gate), SCHEMA)
