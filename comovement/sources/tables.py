"""The given tables with explicit schemas, and point files in four formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

POINT_SCHEMA = "traj long, t long, x double, y double, pid long"
MATCH_COLUMNS = ("r_traj", "r_from", "r_to", "r_t_from", "r_t_to", "s_traj", "s_from", "s_to", "s_t_from", "s_t_to", "lifespan_us", "n_r", "n_s")

SCHEMAS = {
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "supplier": "s_suppkey long, s_name string, s_nationkey long",
    "nation": "n_nationkey long, n_name string, n_regionkey long",
    "region": "r_regionkey long, r_name string",
}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; types of keys differ between writers, so only footers are trusted for the rest."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_points(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """Canonical points from Parquet, ORC, CSV (with header) or JSON, never inferring types."""
    reader = spark.read.schema(POINT_SCHEMA)
    return (reader.option("header", True) if fmt == "csv" else reader).format(fmt).load(path)


def write_points(pts: DataFrame, path: str, fmt: str = "parquet") -> None:
    writer = pts.select("traj", "t", "x", "y", "pid").write.format(fmt)
    (writer.option("header", True) if fmt == "csv" else writer).save(path)


def write_matches(matches: DataFrame, path: str, fmt: str = "parquet", buckets: int = 16) -> None:
    """Matches by buckets of the reference trajectory, so a lookup of one trajectory prunes to one folder. Each task
    writes a file for each bucket that it has rows of, in order; rows are not shuffled."""
    from pyspark.sql import functions as F

    bucketed = matches.withColumn("r_bucket", F.pmod("r_traj", F.lit(buckets)).cast("int"))
    bucketed.sortWithinPartitions("r_bucket", "r_traj", "r_from").write.format(fmt).partitionBy("r_bucket").save(path)


