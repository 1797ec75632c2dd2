"""The k nearest points, against all candidates ranked by window functions."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from comovement import points, registry
from comovement.operators import general, nearest


def ranked(left, right, k, eps):
    r = left.selectExpr("traj r_traj", "seq r_seq", "t r_t", "x r_x", "y r_y")
    s = right.selectExpr("traj s_traj", "seq s_seq", "t s_t", "x s_x", "y s_y")
    near = general.band_join(r, s, "r_t", "s_t", eps).where("r_traj <> s_traj")
    near = near.withColumn("d2", (F.col("r_x") - F.col("s_x")) * (F.col("r_x") - F.col("s_x")) + (F.col("r_y") - F.col("s_y")) * (F.col("r_y") - F.col("s_y")))
    return general.top_per(near, ["r_traj", "r_seq"], ["d2", "s_traj", "s_seq"], k).select("r_traj", "r_seq", "s_traj", "s_seq", "d2", "rank")


def rows(df):
    return sorted(str(tuple(r)) for r in df.collect())


@pytest.fixture(scope="module")
def odd(spark):
    """Ties in time and place, many copies of a place, far and infinite coordinates, one trajectory alone in its time."""
    rng = np.random.default_rng(3)
    n = 700
    found = [(int(k), int(t), float(x), float(y), i) for i, (k, t, x, y) in enumerate(zip(rng.integers(0, 9, n), rng.integers(-300, 300, n), rng.integers(0, 40, n) / 4, rng.integers(0, 6, n)))]
    found += [(k, 40, 3.25, 2.0, 1000 + k) for k in range(20)] + [(5, 5000 + t, 1.0, 1.0, 2000 + t) for t in range(4)] + [(6, 5002, 1e9, -1e9, 3000)]
    found += [(k, 10 * k, float("inf"), float("-inf") if k % 2 else 1.0, 4000 + k) for k in range(4)]
    return points.with_sequence(spark.createDataFrame(found, "traj long, t long, x double, y double, pid long")).persist()


@pytest.mark.parametrize("k, eps", [(1, 0), (3, 20), (7, 4000)])
def test_as_ranked(spark, odd, k, eps, monkeypatch):
    monkeypatch.setattr(nearest, "PIECE", 97)
    assert rows(nearest.knn(odd, odd, k, eps)) == rows(ranked(odd, odd, k, eps))
    one, other = odd.where("traj < 4"), odd.where("traj >= 3")
    assert rows(nearest.knn(one, other, k, eps)) == rows(ranked(one, other, k, eps))


def test_candidates_are_not_shuffled(spark, sf_dir, odd):
    assert "Join" not in registry.QUERIES["op_knn"](spark, sf_dir)._jdf.queryExecution().executedPlan().toString()
    assert nearest.knn(odd, odd.where("false"), 3, 5).count() == nearest.knn(odd.where("false"), odd, 3, 5).count() == 0
