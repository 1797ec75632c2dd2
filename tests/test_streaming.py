"""Stream forms that the registered queries do not show: open runs, late rows, duplicates."""

from datetime import datetime, timedelta

from pyspark.sql import functions as F

from comovement import points
from comovement.sources.tables import table
from comovement.streaming import joins

HOUR = 3_600_000_000


def staged(spark, rows, schema, path):
    for k, batch in enumerate(rows):
        spark.createDataFrame(batch, schema).coalesce(1).write.parquet(f"{path}/{k}")
    return spark.readStream.schema(schema).option("recursiveFileLookup", "true").option("maxFilesPerTrigger", 1).parquet(path)


def test_late_rows_are_counted_and_repeats_dropped(spark, tmp_path):
    at = lambda h: datetime(2024, 1, 1) + timedelta(hours=h)
    rows = [[(1, at(0)), (1, at(0)), (2, at(10))], [(3, at(20)), (2, at(10))], [(4, at(1)), (5, at(30))]]
    stream = staged(spark, rows, "pid long, ts timestamp", str(tmp_path / "in"))
    query = joins.deduplicated(stream, "1 hour").writeStream.format("memory").queryName("kept").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "c")).start()
    query.awaitTermination()
    assert sorted(r.pid for r in spark.table("kept").collect()) == [1, 2, 3, 5]
    assert sum(joins.late_rows(p) for p in query.recentProgress) == 1


def test_open_runs(spark, tmp_path):
    old = spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        rows = [[(1, 2, 0), (1, 2, 1), (3, 4, 0)], [(1, 2, 2), (1, 2, 9)], [(9, 9, 30)], [(9, 9, 60)]]
        rows = [[(a, b, (h + 100) * HOUR) for a, b, h in batch] for batch in rows]
        stream = staged(spark, rows, "a long, b long, t long", str(tmp_path / "in")).withColumn("ts", F.timestamp_micros("t")).withWatermark("ts", "0 seconds")
        out = joins.run_available(joins.open_runs_stream(stream, 3 * HOUR), "runs").collect()
        assert {(r.a, r.b, r.first // HOUR, r.last // HOUR, r.n) for r in out} >= {(1, 2, 100, 102, 3), (3, 4, 100, 100, 1), (1, 2, 109, 109, 1)}
    finally:
        spark.conf.set("spark.sql.streaming.stateStore.providerClass", old)


def test_sliding_windows(spark, sf_dir):
    out = joins.run_available(joins.copresence_windows(joins.event_stream(spark, sf_dir), "2 days", "1 day"), "slide")
    pts = points.from_events(table(spark, sf_dir, "events"))
    day = 24 * HOUR
    for r in out.orderBy("start_us").limit(3).collect():
        assert r.n_points == pts.where((F.col("t") >= r.start_us) & (F.col("t") < r.start_us + 2 * day)).count()
