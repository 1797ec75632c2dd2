"""SQL: views of the stages, a table function over the refine kernel, and Python aggregates."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .engine import SubtrajectoryJoin
from .operators.refine import components_of
from .params import JoinParams

_PIECE = "r_traj: bigint, s_traj: bigint, r_from: bigint, r_to: bigint, s_from: bigint, s_to: bigint"


class _Pieces:
    """Rows of one pair of trajectories to its maximal mutually covering pieces."""

    def __init__(self):
        self.rows = []

    def eval(self, row):
        self.rows.append((row["r_traj"], row["s_traj"], row["r_seq"], row["s_seq"]))

    def terminate(self):
        import numpy as np

        if self.rows:
            e = np.array(self.rows, np.int64)
            comp = components_of(e[:, 2], e[:, 3])
            for c in np.unique(comp):
                own = e[comp == c]
                yield int(e[0, 0]), int(e[0, 1]), int(own[:, 2].min()), int(own[:, 2].max()), int(own[:, 3].min()), int(own[:, 3].max())


def _path_length(t: pd.Series, x: pd.Series, y: pd.Series) -> float:
    order = t.argsort(kind="stable")
    dx, dy = x.iloc[order].diff(), y.iloc[order].diff()
    return float(((dx * dx + dy * dy) ** 0.5).sum())


def path_length():
    """Grouped aggregate: length of the path through (t, x, y); its native twin is operators.general.speed."""
    return F.pandas_udf(_path_length, "double")


def _haversine(ax: pd.Series, ay: pd.Series, bx: pd.Series, by: pd.Series) -> pd.Series:
    import numpy as np

    ax, ay, bx, by = map(np.radians, (ax, ay, bx, by))
    h = np.sin((by - ay) / 2) ** 2 + np.cos(ay) * np.cos(by) * np.sin((bx - ax) / 2) ** 2
    return pd.Series(2 * 6_371_008.8 * np.arcsin(np.sqrt(np.minimum(h, 1.0))))


def register(spark: SparkSession) -> None:
    """Makes subtrajectory_pairs (table function, PARTITION BY pair), path_length and haversine_m known to SQL."""
    spark.udtf.register("subtrajectory_pairs", F.udtf(_Pieces, returnType=_PIECE.replace(": ", " ")))
    spark.udf.register("path_length", path_length())
    spark.udf.register("haversine_m", F.pandas_udf(_haversine, "double"))


def create_views(pts: DataFrame, params: JoinParams, method: str = "indexed") -> None:
    """Temporary views points, joining_pairs, breaking_points, candidate_misses and matches."""
    stages = SubtrajectoryJoin(params, method).stages(pts)
    for name, view in (("points", "points"), ("jp", "joining_pairs"), ("bp", "breaking_points"), ("misses", "candidate_misses"), ("matches", "matches")):
        stages[name].createOrReplaceTempView(view)
