"""Canonical points (traj, t in microseconds, x, y, pid), their numbering and their summaries."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

COLUMNS = ("traj", "t", "x", "y", "pid")


def unix_micros_ntz(ts: str) -> Column:
    """Microseconds since 1970 of a timestamp without time zone, whatever the session's zone."""
    return F.expr(f"timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', {ts})")


def from_columns(df: DataFrame, traj: str, t: str, x: str, y: str, pid: str) -> DataFrame:
    """Points from SQL expressions; rows with a null key or time, or null or NaN coordinates, are rejected."""
    pts = df.selectExpr(f"cast({traj} as long) traj", f"cast({t} as long) t", f"cast({x} as double) x", f"cast({y} as double) y", f"cast({pid} as long) pid")
    return pts.where("traj is not null and t is not null and x is not null and y is not null and not isnan(x) and not isnan(y)")


def from_events(events: DataFrame) -> DataFrame:
    """Users as trajectories; time filters belong on ``ts`` before this, where Parquet can use them."""
    keyed = events.select("user_id", unix_micros_ntz("ts").alias("t"), "value", F.get_json_object("props", "$.k").alias("k"), "event_id")
    return from_columns(keyed, "user_id", "t", "value", "k", "event_id")


def from_lineitem(lineitem: DataFrame) -> DataFrame:
    """Suppliers as trajectories, one point for each ship date: ties in time are collapsed to least values."""
    keyed = lineitem.select("l_suppkey", unix_micros_ntz("l_shipdate").alias("t"), "l_quantity", (F.col("l_discount") * 1000).alias("d"))
    one = keyed.groupBy("l_suppkey", "t").agg(F.min("l_quantity").alias("q"), F.min("d").alias("d"))
    return from_columns(one, "l_suppkey", "t", "q", "d", "t")


def from_orders(orders: DataFrame, customer: DataFrame) -> DataFrame:
    """Customers as trajectories; short and sparse."""
    joined = orders.select("o_custkey", unix_micros_ntz("o_orderdate").alias("t"), "o_totalprice", "o_orderkey").join(
        customer.select("c_custkey", "c_acctbal"), F.col("o_custkey") == F.col("c_custkey")
    )
    return from_columns(joined, "o_custkey", "t", "o_totalprice / 1000", "c_acctbal / 100", "o_orderkey")


def companions(pts: DataFrame, breaks: bool = True) -> DataFrame:
    """Points plus a jittered twin of every fifth trajectory with planted breaks, or without."""
    far = "if(pmod(pid, 6) = 0, 1000000D, 0D)" if breaks else "0D"
    twin = pts.where("pmod(traj, 5) = 0").selectExpr("traj + 1000000 traj", "t + 60000000 * pmod(pid, 5) t", f"x + pmod(pid, 3) + {far} x", "y", "pid + 10000000 pid")
    return pts.select(*COLUMNS).unionByName(twin)


def warped(pts: DataFrame) -> DataFrame:
    """Time skewed to the cube of the fraction of the span; the span is two numbers on the driver."""
    lo, hi = pts.agg(F.min("t"), F.max("t")).first()
    span = max(1, (hi or 0) - (lo or 0))
    u = (F.col("t") - F.lit(lo or 0)).cast("double") / F.lit(float(span))
    return pts.withColumn("t", F.lit(lo or 0) + F.floor(F.lit(float(span)) * u * u * u).cast("long"))


def portion(pts: DataFrame, i: int, of: int = 5) -> DataFrame:
    """The i-th nested portion: i/of of the points."""
    return pts.where(F.pmod("pid", F.lit(of)) < i)


def with_sequence(pts: DataFrame) -> DataFrame:
    """Adds seq (from 1) and the previous and next sample of the trajectory: one shuffle, once."""
    w = Window.partitionBy("traj").orderBy("t", "pid")
    return pts.select(
        *COLUMNS, F.row_number().over(w).cast("long").alias("seq"),
        *[F.lag(c).over(w).alias(f"prev_{c}") for c in ("t", "x", "y")], *[F.lead(c).over(w).alias(f"next_{c}") for c in ("t", "x", "y")],
    )


def summary(pts: DataFrame) -> DataFrame:
    """n, time span, box and largest gap of each trajectory."""
    gaps = pts.select("traj", "t", "x", "y", (F.col("t") - F.lag("t").over(Window.partitionBy("traj").orderBy("t", "pid"))).alias("gap"))
    return gaps.groupBy("traj").agg(
        F.count("*").alias("n"), F.min("t").alias("t_min"), F.max("t").alias("t_max"), F.min("x").alias("x_min"), F.max("x").alias("x_max"),
        F.min("y").alias("y_min"), F.max("y").alias("y_max"), F.max("gap").alias("max_gap"),
    )


def to_arrays(pts: DataFrame) -> DataFrame:
    """One row for each trajectory with its points in order (needs seq)."""
    return pts.groupBy("traj").agg(F.array_sort(F.collect_list(F.struct("seq", "t", "x", "y", "pid"))).alias("points"))


def from_arrays(nested: DataFrame) -> DataFrame:
    return nested.select("traj", F.explode("points").alias("p")).select("traj", "p.t", "p.x", "p.y", "p.pid", "p.seq")


def split_on_gap(pts: DataFrame, gap_us: int) -> DataFrame:
    """Adds trip (from 1) to each point: a new trip starts after an idle gap longer than gap_us."""
    w = Window.partitionBy("traj").orderBy("t", "pid")
    starts = pts.withColumn("_new", F.when(F.col("t") - F.lag("t").over(w) > gap_us, 1).otherwise(0))
    return starts.withColumn("trip", (F.sum("_new").over(w) + 1).cast("long")).drop("_new")


def cut(pts: DataFrame, pieces: DataFrame) -> DataFrame:
    """Points of pieces (traj, seq_from, seq_to); an equi-join on traj with the range as residual."""
    named = pieces.select(F.col("traj").alias("_traj"), "seq_from", "seq_to")
    return pts.join(named, (F.col("traj") == F.col("_traj")) & F.col("seq").between(F.col("seq_from"), F.col("seq_to"))).drop("_traj")


def clean(pts: DataFrame, max_speed: float | None = None, box: tuple[float, float, float, float] | None = None, t_range: tuple[int, int] | None = None, trajectories: list[int] | None = None, min_points: int = 1) -> DataFrame:
    """Filters before numbering: box, time range, trajectories, repeated samples, speed (per second), length."""
    if box:
        pts = pts.where(F.col("x").between(box[0], box[2]) & F.col("y").between(box[1], box[3]))
    if t_range:
        pts = pts.where((F.col("t") >= t_range[0]) & (F.col("t") < t_range[1]))
    if trajectories is not None:
        pts = pts.where(F.col("traj").isin(trajectories))
    w = Window.partitionBy("traj").orderBy("t", "pid")
    pts = pts.withColumn("_n", F.row_number().over(Window.partitionBy("traj", "t").orderBy("pid"))).where("_n = 1").drop("_n")
    if max_speed is not None:
        moved = F.sqrt((F.col("x") - F.lag("x").over(w)) ** 2 + (F.col("y") - F.lag("y").over(w)) ** 2)
        pts = pts.withColumn("_v", moved / ((F.col("t") - F.lag("t").over(w)) / 1e6)).where(F.col("_v").isNull() | (F.col("_v") <= max_speed)).drop("_v")
    if min_points > 1:
        pts = pts.withColumn("_n", F.count("*").over(Window.partitionBy("traj"))).where(F.col("_n") >= min_points).drop("_n")
    return pts


def common_lifespans(left: DataFrame, right: DataFrame, least_us: int, width_us: int) -> DataFrame:
    """(r_traj, s_traj, lifespan_us) of summaries that share at least least_us >= 0, by bucket overlap."""
    from .operators.general import overlap_join

    pairs = overlap_join(left.selectExpr("traj r_traj", "t_min r_lo", "t_max r_hi"), right.selectExpr("traj s_traj", "t_min s_lo", "t_max s_hi"), ("r_lo", "r_hi"), ("s_lo", "s_hi"), width_us)
    return pairs.select("r_traj", "s_traj", (F.least("r_hi", "s_hi") - F.greatest("r_lo", "s_lo")).alias("lifespan_us")).where(F.col("lifespan_us") >= least_us)
