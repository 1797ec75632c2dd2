"""Operators around the methods: band, overlap and as-of joins, runs, rollups, frames, rankings."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def band_join(left: DataFrame, right: DataFrame, left_t: str, right_t: str, radius: int, keys: Sequence[tuple[str, str]] = ()) -> DataFrame:
    """Pairs with |left_t - right_t| <= radius: an equi-join on buckets of that width, the band as residual."""
    width = max(1, radius)
    own = left.withColumn("_b", F.floor(F.col(left_t) / F.lit(width)))
    near = right.withColumn("_b2", F.explode(F.sequence(F.floor(F.col(right_t) / F.lit(width)) - 1, F.floor(F.col(right_t) / F.lit(width)) + 1)))
    on = (F.col("_b") == F.col("_b2")) & (F.abs(F.col(left_t) - F.col(right_t)) <= radius)
    for a, b in keys:
        on = on & (F.col(a) == F.col(b))
    return own.join(near, on).drop("_b", "_b2")


def overlap_join(left: DataFrame, right: DataFrame, left_span: tuple[str, str], right_span: tuple[str, str], width: int) -> DataFrame:
    """Pairs of closed intervals that overlap, each found in the first bucket that both meet."""
    bucket = lambda c: F.floor(F.col(c) / F.lit(width))
    a = left.withColumn("_a", F.explode(F.sequence(bucket(left_span[0]), bucket(left_span[1]))))
    b = right.withColumn("_b", F.explode(F.sequence(bucket(right_span[0]), bucket(right_span[1]))))
    meet = (F.col(left_span[0]) <= F.col(right_span[1])) & (F.col(right_span[0]) <= F.col(left_span[1]))
    first = F.col("_a") == F.greatest(bucket(left_span[0]), bucket(right_span[0]))
    return a.join(b, (F.col("_a") == F.col("_b")) & meet & first).drop("_a", "_b")


def asof_join(left: DataFrame, right: DataFrame, by: str, on: str, value: str, direction: str = "backward", tolerance: int | None = None) -> DataFrame:
    """Left rows with right's value and time at the nearest time (ties: the earlier, then the lesser value).

    One sort by (by, on) of the union of both sides instead of a join."""
    v = F.struct(F.col(on).alias("t"), F.col(value).alias("v"))
    tagged = left.select(*left.columns, F.lit(None).cast(right.select(v.alias("s")).schema["s"].dataType).alias("_r"), F.lit(1).alias("_side")).unionByName(
        right.groupBy(by, on).agg(F.min(value).alias(value)).select(by, on, v.alias("_r"), F.lit(0).alias("_side")), allowMissingColumns=True
    )
    back = Window.partitionBy(by).orderBy(on, "_side").rowsBetween(Window.unboundedPreceding, 0)
    ahead = Window.partitionBy(by).orderBy(F.col(on).desc(), "_side").rowsBetween(Window.unboundedPreceding, 0)
    both = tagged.withColumn("_p", F.last("_r", ignorenulls=True).over(back)).withColumn("_n", F.last("_r", ignorenulls=True).over(ahead)).where("_side = 1")
    before, after = F.col(on) - F.col("_p.t"), F.col("_n.t") - F.col(on)
    found = {"backward": F.col("_p"), "forward": F.col("_n"), "nearest": F.when(F.col("_n").isNull() | (before <= after), F.col("_p")).otherwise(F.col("_n"))}[direction]
    out = both.withColumn("_f", found)
    if tolerance is not None:
        out = out.withColumn("_f", F.when(F.abs(F.col(on) - F.col("_f.t")) <= tolerance, F.col("_f")))
    return out.select(*left.columns, F.col("_f.t").alias("match_t"), F.col("_f.v").alias("match_value"))


def top_per(df: DataFrame, keys: Sequence[str], order: Sequence[Column | str], k: int, name: str = "rank") -> DataFrame:
    """The first k rows of each key; Spark keeps k rows per key before the shuffle."""
    return df.withColumn(name, F.row_number().over(Window.partitionBy(*keys).orderBy(*order)).cast("long")).where(F.col(name) <= k)


def runs(df: DataFrame, keys: Sequence[str], seq: str) -> DataFrame:
    """Maximal runs of consecutive numbers: keys, seq_from, seq_to, n."""
    island = F.col(seq) - F.dense_rank().over(Window.partitionBy(*keys).orderBy(seq))
    return df.withColumn("_i", island).groupBy(*keys, "_i").agg(F.min(seq).alias("seq_from"), F.max(seq).alias("seq_to"), F.countDistinct(seq).alias("n")).drop("_i")


def merge_intervals(df: DataFrame, keys: Sequence[str], start: str, end: str, slack: int = 0) -> DataFrame:
    """Union of intervals that overlap or lie within slack of each other: keys, start, end, n."""
    w = Window.partitionBy(*keys).orderBy(start, end)
    reach = F.max(end).over(w.rowsBetween(Window.unboundedPreceding, -1))
    marked = df.withColumn("_new", F.when(reach.isNull() | (F.col(start) > reach + slack), 1).otherwise(0))
    return marked.withColumn("_g", F.sum("_new").over(w)).groupBy(*keys, "_g").agg(F.min(start).alias(start), F.max(end).alias(end), F.count("*").alias("n")).drop("_g")


def compare(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: rows only in a, only in b, in both (as bags), repeated rows of a."""
    cols = a.columns
    marked = a.select(*cols, F.lit(1).alias("na"), F.lit(0).alias("nb")).unionByName(b.select(*cols, F.lit(0).alias("na"), F.lit(1).alias("nb")))
    per_row = marked.groupBy(*cols).agg(F.sum("na").alias("na"), F.sum("nb").alias("nb"))
    total = lambda e, name: F.coalesce(F.sum(e), F.lit(0)).cast("long").alias(name)
    return per_row.agg(
        total(F.greatest(F.col("na") - F.col("nb"), F.lit(0)), "only_left"), total(F.greatest(F.col("nb") - F.col("na"), F.lit(0)), "only_right"),
        total(F.least("na", "nb"), "both"), total(F.greatest(F.col("na") - 1, F.lit(0)), "repeated_left"),
    )


def speed(pts: DataFrame) -> DataFrame:
    """Step length from the previous sample and running path length; sums of per-row values in order."""
    w = Window.partitionBy("traj").orderBy("t", "pid")
    dx, dy = F.col("x") - F.lag("x").over(w), F.col("y") - F.lag("y").over(w)
    step = pts.withColumn("step", F.coalesce(F.sqrt(dx * dx + dy * dy), F.lit(0.0)))
    return step.withColumn("path", F.sum("step").over(w.rowsBetween(Window.unboundedPreceding, 0)))


def local_density(pts: DataFrame, eps_t_us: int) -> DataFrame:
    """Samples of the same trajectory within +-eps_t of each sample."""
    w = Window.partitionBy("traj").orderBy("t").rangeBetween(-eps_t_us, eps_t_us)
    return pts.select("traj", "pid", F.count("*").over(w).alias("n_near"))


def partner_map(matches: DataFrame) -> DataFrame:
    """For each reference trajectory a map partner -> longest lifespan."""
    best = matches.groupBy("r_traj", "s_traj").agg(F.max("lifespan_us").alias("m"))
    return best.groupBy("r_traj").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("s_traj", "m")))).alias("partners"))


def to_geojson(matches: DataFrame) -> DataFrame:
    """A JSON object for each match."""
    return matches.select("r_traj", "s_traj", "r_from", F.to_json(F.struct("r_traj", "r_from", "r_to", "s_traj", "s_from", "s_to", "lifespan_us")).alias("json"))
