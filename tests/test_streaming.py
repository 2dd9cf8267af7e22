"""The monitors on a file stream give what their batch twins give."""

from pyspark.sql import functions as F

from depmine.sources.io import load_stream, write_stream
from depmine.streaming import monitor


def test_stream_equals_batch(spark, tiny, tmp_path):
    batch = spark.read.parquet(f"{tiny}/events.parquet")
    batch.repartition(3).write.parquet(f"{tmp_path}/in")
    stream = load_stream(spark, f"{tmp_path}/in", batch.schema, maxFilesPerTrigger=1)
    query = write_stream(monitor.watch_fd(stream, ["user_id"], "event_type"), f"{tmp_path}/cp", name="refuted", mode="complete")
    query.processAllAvailable()
    query.stop()
    want = {tuple(r) for r in monitor.watch_fd(batch, ["user_id"], "event_type").collect()}
    assert {tuple(r) for r in spark.table("refuted").collect()} == want and want


def test_fold_of_batches(spark, tiny, tmp_path):
    batch = spark.read.parquet(f"{tiny}/events.parquet").select("user_id", "event_type")
    fold = monitor.EvidenceFold(f"{tmp_path}/store", f"{tmp_path}/out", ["user_id"], "event_type")
    for i in range(3):
        fold(batch.where(F.pmod(F.xxhash64("user_id", "event_type"), F.lit(3)) == i), i)
    got = {r["user_id"] for r in spark.read.parquet(f"{tmp_path}/out").collect()}
    assert got == {r["user_id"] for r in monitor.watch_fd(batch, ["user_id"], "event_type").collect()}


def test_late_rows_are_counted(spark, tmp_path):
    """A row two days behind the watermark is dropped and counted."""
    rows = lambda day, n: spark.createDataFrame([(f"2024-01-{day:02d} 00:00:{i:02d}", i) for i in range(n)], "ts string, v int").selectExpr("cast(ts as timestamp) as ts", "v")
    for n, (day, size) in enumerate(((10, 5), (11, 5), (3, 4), (12, 5))):
        rows(day, size).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
        if not n:
            stream = monitor.with_watermark(load_stream(spark, f"{tmp_path}/in", rows(1, 1).schema), "ts", "1 hour")
            query = write_stream(monitor.window_counts(stream, "ts", "1 day"), f"{tmp_path}/cp", name="windows", mode="append")
        query.processAllAvailable()
    dropped = monitor.late_rows(query)
    query.stop()
    assert dropped > 0 and 3 not in {r["window_start"].day for r in spark.table("windows").collect()}
