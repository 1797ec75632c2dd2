"""Structured Streaming forms: interval self-join, late breaks, co-presence windows, sessions, open runs.

State is bounded by watermarks: an interval join keeps 2 eps_t + lateness of points, an open run is
dropped once the watermark passes its last point by eps_t.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor

from ..functions.distance import sq_euclid
from ..params import JoinParams
from ..sources.scratch import scratch
from ..sources.tables import SCHEMAS


def event_stream(spark: SparkSession, sf_dir: str, files: str = "events.parquet") -> DataFrame:
    """Points of the events table as a file stream, with event time ``ts`` (a timestamp)."""
    raw = spark.readStream.schema(SCHEMAS["events"]).option("pathGlobFilter", files).option("recursiveFileLookup", "true").parquet(sf_dir)
    t = F.expr("timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', ts)")
    return raw.select(
        F.col("user_id").alias("traj"), F.timestamp_micros(t).alias("ts"), t.alias("t"), F.col("value").alias("x"),
        F.get_json_object("props", "$.k").cast("double").alias("y"), F.col("event_id").alias("pid"), "event_type",
    )


def _sides(stream: DataFrame, params: JoinParams, lateness: str) -> tuple[DataFrame, DataFrame]:
    width = max(1, params.eps_t_us)
    bucket = F.floor(F.col("t") / F.lit(width))
    marked = stream.withWatermark("ts", lateness)
    r = marked.select(*[F.col(c).alias(f"r_{c}") for c in ("traj", "pid", "t", "ts", "x", "y")], bucket.alias("r_b"))
    s = marked.select(*[F.col(c).alias(f"s_{c}") for c in ("traj", "pid", "t", "ts", "x", "y")], F.explode(F.sequence(bucket - 1, bucket + 1)).alias("s_b"))
    return r, s


def _on(params: JoinParams):
    eps = F.expr(f"interval {params.eps_t_us} microseconds")
    band = F.col("s_ts").between(F.col("r_ts") - eps, F.col("r_ts") + eps) & (F.abs(F.col("r_t") - F.col("s_t")) <= params.eps_t_us)
    near = sq_euclid(F.col("r_x"), F.col("r_y"), F.col("s_x"), F.col("s_y")) <= F.lit(float(params.eps_sp) ** 2)
    return (F.col("r_b") == F.col("s_b")) & band & near & (F.col("r_traj") != F.col("s_traj"))


def joining_pairs_stream(stream: DataFrame, params: JoinParams, lateness: str = "0 seconds") -> DataFrame:
    """Directed joining pairs (r_traj, r_pid, s_traj, s_pid), each once, as both points arrive."""
    r, s = _sides(stream, params, lateness)
    return r.join(s, _on(params)).select("r_traj", "r_pid", "s_traj", "s_pid")


def breaking_points_stream(stream: DataFrame, params: JoinParams, lateness: str = "0 seconds") -> DataFrame:
    """Pairs as above, and a row with null partner for a point that has none once the watermark rules it out."""
    r, s = _sides(stream, params, lateness)
    return r.join(s, _on(params), "left_outer").select("r_traj", "r_pid", "r_t", "s_traj", "s_pid")


def copresence_windows(stream: DataFrame, size: str, slide: str | None = None, lateness: str = "0 seconds") -> DataFrame:
    """Points and (about how many) trajectories in each tumbling or sliding window."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    counted = stream.withWatermark("ts", lateness).groupBy(w).agg(F.count("*").alias("n_points"), F.approx_count_distinct("traj", 0.01).alias("n_trajectories"))
    return counted.select(F.unix_micros("window.start").alias("start_us"), "n_points", "n_trajectories")


def trips_stream(stream: DataFrame, gap: str, lateness: str = "0 seconds") -> DataFrame:
    """Sessions of each trajectory that end after an idle gap."""
    out = stream.withWatermark("ts", lateness).groupBy("traj", F.session_window("ts", gap)).agg(F.count("*").alias("n_points"))
    return out.select("traj", F.unix_micros("session_window.start").alias("start_us"), F.unix_micros("session_window.end").alias("end_us"), "n_points")


def deduplicated(stream: DataFrame, lateness: str) -> DataFrame:
    """One row for each pid among rows within the lateness of each other."""
    return stream.withWatermark("ts", lateness).dropDuplicatesWithinWatermark(["pid"])


class OpenRuns(StatefulProcessor):
    """Per pair of trajectories, the run of joint presence now open; emitted when a gap longer than ``gap_us``
    or a timer past its last point closes it."""

    def __init__(self, gap_us: int):
        self.gap_us = gap_us

    def init(self, handle) -> None:
        self.handle = handle
        self.run = handle.getValueState("run", "first long, last long, n long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N803
        times = sorted(t for pdf in rows for t in pdf["t"].tolist())
        run = list(self.run.get()) if self.run.exists() else None
        closed = []
        for t in times:
            if run and t - run[1] > self.gap_us:
                closed.append((*key, *run))
                run = None
            run = [min(run[0], t), max(run[1], t), run[2] + 1] if run else [t, t, 1]
        if run:
            self.run.update(tuple(run))
            for old in self.handle.listTimers():
                self.handle.deleteTimer(old)
            self.handle.registerTimer((run[1] + self.gap_us) // 1000 + 1)
        yield pd.DataFrame(closed, columns=["a", "b", "first", "last", "n"])

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:  # noqa: N803
        if self.run.exists():
            out = (*key, *self.run.get())
            self.run.clear()
            yield pd.DataFrame([out], columns=["a", "b", "first", "last", "n"])

    def close(self) -> None:
        pass


def open_runs_stream(pairs: DataFrame, gap_us: int) -> DataFrame:
    """Closed runs of pairs (a, b, t long, ts watermarked): needs the RocksDB state store."""
    return pairs.groupBy("a", "b").transformWithStateInPandas(OpenRuns(gap_us), "a long, b long, first long, last long, n long", "Append", "EventTime")


def run_available(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Runs a stream over all available input into a folder of Parquet files and reads them."""
    spark = stream.sparkSession
    path = scratch(spark, name)
    query = stream.writeStream.format("parquet").option("path", f"{path}/rows").option("checkpointLocation", f"{path}/state").outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/rows")


def late_rows(progress) -> int:
    """Rows dropped for being behind the watermark, from a query's progress."""
    return sum(op.numRowsDroppedByWatermark for op in progress.stateOperators)
