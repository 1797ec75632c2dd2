"""The join from end to end."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .functions.distance import CELL_SAFE
from .operators import blocks, classify, pointjoin, refine
from .params import JoinParams
from .plans import planner, quadtree
from .points import with_sequence
from .sources import store
from .sources.scratch import written


class SubtrajectoryJoin:
    """All pairs of maximal matching subtrajectories.

    method: auto, naive, slab_nested_loop, sweep, basic, prepart, indexed or gridtile (the last for
    delta_t = 0, or with complete=True and a windowed refine, which finds breaks and misses afterwards). refine: exact, rounds (exact, by window functions), windowed_span or windowed_lifespan.
    options: n_slabs, cap_fraction, dedupe, n_parts, nx, ny, nt (grid tiles), materialize (write the pairs before
    refining, as a chain of two jobs does), spatial_index and traj_index (False: indexed without one of its indexes,
    on a prepared store)."""

    def __init__(self, params: JoinParams, method: str = "auto", refine: str = "exact", **options):
        self.params, self.method, self.refine, self.options = params, method, refine, options

    def prepare(self, pts: DataFrame, path: str) -> store.PreparedStore:
        return store.prepare(pts, path, self.options.get("n_slabs"), self.options.get("cap_fraction", 0.03))

    def pairs(self, left: DataFrame, right: DataFrame | None = None, prepared: store.PreparedStore | None = None, carry: tuple[str, ...] = ()) -> DataFrame:
        """Directed joining pairs of numbered points, with further columns of the reference (``carry``). With a
        prepared store, prepart and indexed read the left points from it and join them where they lie."""
        method, tree, slabs = self.method, None, None
        if prepared is not None:
            slabs, tree = prepared.slabs, prepared.tree
        if method == "auto":
            tree = tree or quadtree.build(left, self.options.get("cap_fraction", 0.03))
            method = planner.choose_method(left, self.params, tree)
        if method == "gridtile" and self.params.delta_t_us > 0 and not (self.options.get("complete") and self.refine.startswith("windowed_")):
            raise ValueError("gridtile gives pairs only: it is valid for delta_t = 0, or complete=True with a windowed refine")
        if prepared is not None and right is None and not carry and method in ("prepart", "indexed") and self.params.metric in CELL_SAFE:
            jp = pointjoin.stored(left.sparkSession, prepared, self.params, method == "indexed" and self.options.get("spatial_index", True), self.options.get("traj_index", True))
        else:
            known = {k: v for k, v in self.options.items() if k in ("n_slabs", "cap_fraction", "dedupe", "n_parts", "nx", "ny", "nt")}
            jp = pointjoin.joining_pairs(left, right, self.params, method, slabs=slabs, tree=tree, carry=carry, **known)
        return written(jp, "pairs") if self.options.get("materialize") else jp

    def stages(self, pts: DataFrame) -> dict[str, DataFrame]:
        """Numbered points, joining pairs, breaking points, candidate misses and matches of a self-join."""
        numbered = pts if "seq" in pts.columns else with_sequence(pts)
        jp = self.pairs(numbered)
        return {"points": numbered, "jp": jp, "bp": classify.breaking_points(numbered, jp), "misses": classify.candidate_misses(numbered, jp), "matches": self._refined(jp, numbered, None)}

    def _refined(self, jp: DataFrame, left: DataFrame, right: DataFrame | None) -> DataFrame:
        if self.refine.startswith("windowed_"):
            if "r_next_t" not in jp.columns:
                jp = jp.join(left.select(F.col("traj").alias("r_traj"), F.col("seq").alias("r_seq"), F.col("next_t").alias("r_next_t")), ["r_traj", "r_seq"])
            jp = written(jp, "pairs")  # read three times below
            bp, misses = classify.breaking_points(left, jp), classify.miss_positions(left if right is None else right, jp)
            return refine.windowed(jp, bp, misses, self.params, self.refine.removeprefix("windowed_"))
        once = jp.where(F.col("r_traj") < F.col("s_traj")) if right is None else jp
        return refine.by_rounds(once, self.params) if self.refine == "rounds" else refine.maximal_matches(once, self.params)

    def _in_blocks(self, pts: DataFrame, prepared: store.PreparedStore | None, each: Callable | None = None, schema: str = refine.SCHEMA, sides: bool = False, least_us: int | None = None) -> DataFrame | None:
        """The exact matches of a self-join by prepart or indexed (with the tree's cells), pairs found and refined in one
        task; None for what is not joined so."""
        if self.method not in ("auto", "prepart", "indexed") or self.refine != "exact" or self.options.get("materialize") or self.params.metric not in CELL_SAFE:
            return None
        tree = None if prepared is None else prepared.tree
        method, groups = self.method, blocks.groups_of(pts.count())
        path = blocks.dealt(pts, groups)  # what comes before the blocks is read from there
        own = blocks.points_of(pts.sparkSession, path)
        if tree is None and method != "prepart":
            tree = quadtree.build(own, self.options.get("cap_fraction", 0.03))
        if method == "auto":
            method = planner.choose_method(own, self.params, tree)
        return blocks.matches(own, self.params, tree if method == "indexed" and self.options.get("spatial_index", True) else None, groups, each, schema, path, sides, least_us)

    def run(self, left: DataFrame, right: DataFrame | None = None, prepared: store.PreparedStore | None = None) -> DataFrame:
        """Matches; a self-join gives each unordered pair once (r_traj < s_traj), windowed forms both directions."""
        found = self._in_blocks(left, prepared) if right is None else None
        if found is not None:
            return found
        number = lambda p: p if "seq" in p.columns else with_sequence(p)
        left = number(left)
        right = None if right is None else number(right)
        carry = ("next_t",) if self.refine.startswith("windowed_") else ()
        return self._refined(self.pairs(left, right, prepared, carry), left, right)

    def reduced(self, pts: DataFrame, each: Callable, schema: str, prepared: store.PreparedStore | None = None, sides: bool = False, least_us: int | None = None) -> DataFrame:
        """What ``each`` makes of the exact matches of a self-join where they are found (see ``blocks.matches``): for uses
        that need far fewer rows than there are matches."""
        found = self._in_blocks(pts, prepared, each, schema, sides, least_us)
        if found is None:
            raise ValueError(f"{self.method}, {self.refine}: matches are not found in blocks")
        return found

    def explain_cost(self, pts: DataFrame) -> DataFrame:
        from . import metrics

        numbered = pts if "seq" in pts.columns else with_sequence(pts)
        return metrics.predicted_cost(numbered, self.params, quadtree.build(numbered, self.options.get("cap_fraction", 0.03)))
