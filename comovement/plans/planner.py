"""Choice of a point-join method from measured replication."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..params import JoinParams
from .quadtree import Quadtree

MOST_CELLS = 6.0
"""Mean cells a point may meet before cell pruning stops paying."""


def choose_method(pts: DataFrame, params: JoinParams, tree: Quadtree | None, sample: float = 0.01) -> str:
    """'indexed' unless the radius meets so many cells that time slabs alone are cheaper."""
    if tree is None or len(tree.leaves) < 2:
        return "prepart"
    probe = pts.sample(sample, seed=7).limit(10_000)
    met = probe.agg(F.avg(F.size(tree.touched_cells(F.col("x"), F.col("y"), params.eps_sp)))).first()[0]
    return "indexed" if (met or 1.0) <= MOST_CELLS and len(tree.leaves) > 2 * (met or 1.0) else "prepart"
