"""Breaking points, non-joining pairs and boundary misses of joining pairs."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def breaking_points(pts: DataFrame, jp: DataFrame) -> DataFrame:
    """Points without any joining pair: traj, seq, t."""
    joined = jp.select(F.col("r_traj").alias("traj"), F.col("r_seq").alias("seq")).distinct()
    return pts.select("traj", "seq", "t").join(joined, ["traj", "seq"], "left_anti")


def pairs_and_breaks(pts: DataFrame, jp: DataFrame) -> DataFrame:
    """Joining pairs and breaking points in one outer join, with kind JP or BP."""
    ref = pts.select(F.col("traj").alias("r_traj"), F.col("seq").alias("r_seq"), F.col("t").alias("r_t"))
    out = ref.join(jp.drop("r_t"), ["r_traj", "r_seq"], "left")
    return out.withColumn("kind", F.when(F.col("s_traj").isNull(), "BP").otherwise("JP"))


def non_joining(pts: DataFrame, jp: DataFrame) -> DataFrame:
    """All pairs of non-breaking points of different trajectories that do not join; for small inputs."""
    live = pts.select("traj", "seq").join(jp.select(F.col("r_traj").alias("traj"), F.col("r_seq").alias("seq")).distinct(), ["traj", "seq"], "left_semi")
    every = live.selectExpr("traj r_traj", "seq r_seq").crossJoin(live.selectExpr("traj s_traj", "seq s_seq")).where("r_traj <> s_traj")
    return every.join(jp, ["r_traj", "r_seq", "s_traj", "s_seq"], "left_anti")


def cover_counts(pts: DataFrame, jp: DataFrame) -> DataFrame:
    """One row: all directed pairs of points of different trajectories = JP + NJP + pairs with a breaking point."""
    sizes = pts.groupBy("traj").agg(F.count("*").alias("n"))
    bp = breaking_points(pts, jp).groupBy("traj").agg(F.count("*").alias("b"))
    per = sizes.join(bp, "traj", "left").select("n", (F.col("n") - F.coalesce("b", F.lit(0))).alias("m"))
    totals = per.agg(F.sum("n").alias("n"), F.sum(F.col("n") * F.col("n")).alias("nn"), F.sum("m").alias("m"), F.sum(F.col("m") * F.col("m")).alias("mm"))
    joined = jp.agg(F.count("*").alias("n_jp"))
    both = totals.join(F.broadcast(joined))  # one row each
    live = F.col("m") * F.col("m") - F.col("mm")
    every = F.col("n") * F.col("n") - F.col("nn")
    return both.select(every.alias("n_pairs"), "n_jp", (live - F.col("n_jp")).alias("n_njp"), (every - live).alias("n_with_bp"))


def _positions(jp: DataFrame) -> DataFrame:
    """Distinct (r_traj, s_traj, s_seq) that some point of r joins."""
    return jp.select("r_traj", "s_traj", "s_seq").distinct()


def effective_misses(pts: DataFrame, jp: DataFrame) -> DataFrame:
    """Borders of s's runs: non-breaking points next to a point that joins r, joining no point of r."""
    hit = _positions(jp)
    beside = hit.select("r_traj", "s_traj", F.explode(F.array(F.col("s_seq") - 1, F.col("s_seq") + 1)).alias("s_seq")).distinct()
    live = jp.select(F.col("r_traj").alias("s_traj"), F.col("r_seq").alias("s_seq")).distinct()
    return beside.join(hit, ["r_traj", "s_traj", "s_seq"], "left_anti").join(live, ["s_traj", "s_seq"], "left_semi").select("r_traj", "s_traj", "s_seq")


def literal_misses(pts: DataFrame, jp: DataFrame) -> DataFrame:
    """Boundary misses by the wording: r_i is the one point of r nearest in time to s_j, neither breaks, they
    do not join, and a neighbour of s_j joins some other point of r. Rows (r_traj, r_seq, s_traj, s_seq).

    The nearest point of r comes from a union of both trajectories' points sorted by time."""
    live = jp.select(F.col("r_traj").alias("traj"), F.col("r_seq").alias("seq")).distinct()
    beside = jp.select("r_traj", F.col("r_seq").alias("p_seq"), "s_traj", F.explode(F.array(F.col("s_seq") - 1, F.col("s_seq") + 1)).alias("s_seq"))
    beside = beside.groupBy("r_traj", "s_traj", "s_seq").agg(F.min("p_seq").alias("p_lo"), F.max("p_seq").alias("p_hi"))
    alive = live.select(F.col("traj").alias("s_traj"), F.col("seq").alias("s_seq"))
    cand = beside.join(alive, ["s_traj", "s_seq"], "left_semi").join(pts.select(F.col("traj").alias("s_traj"), F.col("seq").alias("s_seq"), F.col("t").alias("s_t")), ["s_traj", "s_seq"])
    asked = cand.select(F.col("r_traj").alias("traj"), F.col("s_t").alias("t"), F.struct("s_traj", "s_seq", "p_lo", "p_hi").alias("ask"), F.lit(None).cast("struct<t:bigint,seq:bigint>").alias("pt"))
    given = pts.select("traj", "t", F.lit(None).cast(asked.schema["ask"].dataType).alias("ask"), F.struct("t", "seq").alias("pt"))
    order = [F.col("t"), F.col("ask").isNotNull()]
    back = Window.partitionBy("traj").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    ahead = Window.partitionBy("traj").orderBy(F.col("t").desc(), F.col("ask").isNotNull()).rowsBetween(Window.unboundedPreceding, 0)
    both = asked.unionByName(given).withColumn("p", F.last("pt", ignorenulls=True).over(back)).withColumn("n", F.last("pt", ignorenulls=True).over(ahead))
    times = pts.groupBy("traj", "t").agg(F.count("*").alias("n_at"))
    both = both.where("ask is not null")
    before, after = F.col("t") - F.col("p.t"), F.col("n.t") - F.col("t")
    nearest = F.when(F.col("n").isNull() | (before < after), F.col("p")).when(F.col("p").isNull() | (after < before), F.col("n")).when(F.col("p.seq") == F.col("n.seq"), F.col("p"))
    near = both.select(F.col("traj").alias("r_traj"), "ask.*", nearest.alias("near")).where("near is not null").select("r_traj", F.col("near.seq").alias("r_seq"), F.col("near.t").alias("near_t"), "s_traj", "s_seq", "p_lo", "p_hi")
    near = near.join(times.select(F.col("traj").alias("r_traj"), F.col("t").alias("near_t"), "n_at"), ["r_traj", "near_t"]).where("n_at = 1 and (p_lo <> r_seq or p_hi <> r_seq)")
    alive_r = live.select(F.col("traj").alias("r_traj"), F.col("seq").alias("r_seq"))
    return near.join(alive_r, ["r_traj", "r_seq"], "left_semi").join(jp, ["r_traj", "r_seq", "s_traj", "s_seq"], "left_anti").select("r_traj", "r_seq", "s_traj", "s_seq")


def candidate_misses(pts: DataFrame, jp: DataFrame) -> DataFrame:
    """For each joining pair the point before and the point after the partner, unless it joins the same
    reference trajectory: rows (r_traj, r_seq, s_traj, s_seq), a superset of what the refine step needs."""
    ends = pts.groupBy("traj").agg(F.max("seq").alias("last")).select(F.col("traj").alias("s_traj"), "last")
    beside = jp.select("r_traj", "r_seq", "s_traj", F.explode(F.array(F.col("s_seq") - 1, F.col("s_seq") + 1)).alias("s_seq")).distinct()
    inside = beside.join(ends, "s_traj").where("s_seq >= 1 and s_seq <= last").drop("last")
    return inside.join(_positions(jp), ["r_traj", "s_traj", "s_seq"], "left_anti").select("r_traj", "r_seq", "s_traj", "s_seq")


def miss_positions(pts: DataFrame, jp: DataFrame) -> DataFrame:
    """The candidate misses by partner alone: points (r_traj, s_traj, s_seq) beside a run of joined ones.

    One sort of the joined positions; each hole is named once from the left and, if wider, once from the right."""
    w = Window.partitionBy("r_traj", "s_traj").orderBy("s_seq")
    ends = pts.groupBy("traj").agg(F.max("seq").alias("last")).select(F.col("traj").alias("s_traj"), "last")
    here = _positions(jp).withColumn("before", F.lag("s_seq").over(w)).withColumn("after", F.lead("s_seq").over(w))
    left = F.when(F.col("before").isNull() | (F.col("before") < F.col("s_seq") - 2), F.col("s_seq") - 1)
    right = F.when(F.col("after").isNull() | (F.col("after") > F.col("s_seq") + 1), F.col("s_seq") + 1)
    beside = here.select("r_traj", "s_traj", F.explode(F.array_compact(F.array(left, right))).alias("s_seq"))
    return beside.join(ends, "s_traj").where("s_seq >= 1 and s_seq <= last").select("r_traj", "s_traj", "s_seq")
