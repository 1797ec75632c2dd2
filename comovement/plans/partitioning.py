"""Time slabs: uniform and equi-depth bounds, assignment, expansion by the tolerance, ownership."""

from __future__ import annotations

import bisect
import math
import warnings
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Slabs:
    """Disjoint half-open slabs given by their inner bounds; the first and last are unbounded."""

    bounds: tuple[int, ...]
    """The first instant of slabs 1, 2, ..."""

    @property
    def count(self) -> int:
        return len(self.bounds) + 1

    def of(self, t: Column) -> Column:
        """Slab of a time. A coarse uniform grid gives the first bound to look at, so a point compares
        itself with the bounds of its coarse cell only, however many slabs there are."""
        if not self.bounds:
            return F.lit(0)
        lo, hi = self.bounds[0], self.bounds[-1]
        n = min(1024, len(self.bounds))
        width = max(1, -(-(hi - lo + 1) // n))
        firsts = [bisect.bisect_left(self.bounds, lo + i * width) for i in range(n)] + [len(self.bounds)]
        cell = F.least(F.greatest(F.floor((t - F.lit(lo)) / F.lit(width)).cast("long"), F.lit(0)), F.lit(n - 1)).cast("int")
        starts, bounds = F.array(*[F.lit(i) for i in firsts]), F.array(*[F.lit(b) for b in self.bounds])
        first = F.element_at(starts, cell + 1)
        here = F.slice(bounds, first + 1, F.element_at(starts, cell + 2) - first)
        return F.when(t < F.lit(lo), 0).otherwise(first + F.size(F.filter(here, lambda b: b <= t))).cast("int")

    def limits(self) -> list[tuple[int, int | None, int | None]]:
        edges = [None, *self.bounds, None]
        return [(k, edges[k], edges[k + 1]) for k in range(self.count)]


def uniform(pts: DataFrame, n: int, largest_gap_us: int | None = None) -> Slabs:
    """n slabs of equal duration; only the ends of the time span come to the driver.

    Warns where the slabs are narrower than the largest gap between samples of a trajectory, if that is given
    (``points.summary`` has it): a point's neighbours may then be slabs away."""
    lo, hi = pts.agg(F.min("t"), F.max("t")).first()
    if lo is None:
        return Slabs(())
    width = max(1, -(-(hi - lo + 1) // n))
    if largest_gap_us is not None and width < largest_gap_us:
        warnings.warn(f"slabs of {width} us are narrower than the largest gap of {largest_gap_us} us", stacklevel=2)
    return Slabs(tuple(lo + k * width for k in range(1, n)))


def equi_depth(pts: DataFrame, m: int, accuracy: int = 10_000) -> Slabs:
    """m slabs of about equal counts from a mergeable quantile sketch of all times."""
    if m < 2:
        return Slabs(())
    found = pts.agg(F.percentile_approx("t", [k / m for k in range(1, m)], accuracy)).first()[0]
    return Slabs(tuple(sorted({int(b) + 1 for b in found or ()})))


def plan_slabs(total_bytes: int, block_bytes: int, nodes: int) -> tuple[int, int]:
    """(slabs, neighbouring slabs kept on a node): one slab for each block, dealt evenly."""
    m = max(1, math.ceil(total_bytes / block_bytes))
    return m, math.ceil(m / max(1, nodes))


def expand(pts: DataFrame, slabs: Slabs, eps_t_us: int) -> DataFrame:
    """Each point in every slab that its +-eps interval meets, with is_home."""
    own = pts.withColumn("home_slab", slabs.of(F.col("t")))
    wide = own.withColumn("slab", F.explode(F.sequence(slabs.of(F.col("t") - eps_t_us), slabs.of(F.col("t") + eps_t_us))))
    return wide.withColumn("is_home", F.col("slab") == F.col("home_slab"))


def owns(t: Column, lo: int | None, hi: int | None) -> Column:
    """Whether the half-open slab [lo, hi) owns a time."""
    inside = F.lit(True)
    if lo is not None:
        inside = inside & (t >= lo)
    return inside & (t < hi) if hi is not None else inside


def equi_depth_exact(pts: DataFrame, m: int) -> DataFrame:
    """slab, n, t_from, t_to of exact equi-depth slabs by ntile over the distinct times' counts (ties stay together).

    Times are first counted by day, then ranked within days, so no task sorts all times."""
    day = F.floor(F.col("t") / F.lit(86_400_000_000))
    days = pts.groupBy(day.alias("day")).agg(F.count("*").alias("n"))
    before = days.withColumn("before", F.coalesce(F.sum("n").over(Window.orderBy("day").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    total = F.sum("n").over(Window.partitionBy())
    before = before.select("day", "before", total.alias("total"))
    ranked = pts.select("t", day.alias("day")).withColumn("r", F.rank().over(Window.partitionBy("day").orderBy("t")) - 1).join(before, "day")
    slab = F.expr(f"((before + r) * {m}) div total").cast("int")
    return ranked.groupBy(slab.alias("slab")).agg(F.count("*").alias("n"), F.min("t").alias("t_from"), F.max("t").alias("t_to"))
