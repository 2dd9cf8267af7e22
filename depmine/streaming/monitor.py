"""Monitors of dependencies over streams: more rows can only refute, so keyed state of two values a class suffices."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from depmine.operators.refine import rank_key


def with_watermark(df: DataFrame, column: str, delay: str) -> DataFrame:
    """Zone-less timestamps are read as UTC: a watermark needs an instant."""
    return df.withColumn(column, F.col(column).cast("timestamp")).withWatermark(column, delay)


def watch_fd(df: DataFrame, lhs: list[str], rhs: str) -> DataFrame:
    """Refuted classes of lhs -> rhs with two witnesses; for update mode."""
    seen = df.groupBy(*lhs).agg(F.min(rank_key(rhs)).alias("a"), F.max(rank_key(rhs)).alias("b"))
    return seen.where("not (a <=> b)").select(*lhs, F.col("a.v").cast("string").alias("value_1"), F.col("b.v").cast("string").alias("value_2"))


def watch_ucc(df: DataFrame, attrs: list[str]) -> DataFrame:
    """Keys seen more than once; for update mode."""
    return df.groupBy(*attrs).agg(F.count("*").alias("n_rows")).where("n_rows > 1")


def window_fd(df: DataFrame, ts: str, size: str, lhs: list[str], rhs: str, slide: str | None = None) -> DataFrame:
    """Classes of lhs that hold several values of rhs within one window; state ends with the watermark."""
    at = F.window(ts, size, slide) if slide else F.window(ts, size)
    seen = df.groupBy(at.alias("w"), *lhs).agg(F.min(rank_key(rhs)).alias("a"), F.max(rank_key(rhs)).alias("b"))
    return seen.where("not (a <=> b)").select(F.col("w.start").alias("window_start"), *lhs)


def window_counts(df: DataFrame, ts: str, size: str, slide: str | None = None, value: str | None = None) -> DataFrame:
    """Rows of each tumbling or sliding window, and the estimated number of distinct values."""
    at = F.window(ts, size, slide) if slide else F.window(ts, size)
    more = [F.approx_count_distinct(value).alias("n_values")] if value else []
    return df.groupBy(at.alias("w")).agg(F.count("*").alias("n_rows"), *more).select(F.col("w.start").alias("window_start"), "n_rows", *(["n_values"] if value else []))


def session_counts(df: DataFrame, ts: str, gap: str, key: str) -> DataFrame:
    return df.groupBy(F.session_window(ts, gap).alias("w"), key).agg(F.count("*").alias("n_rows")).select(F.col("w.start").alias("session_start"), key, "n_rows")


def late_rows(query) -> int:
    """Rows that a running or ended query has dropped behind its watermark, over the batches that it still reports."""
    return sum(int(state["numRowsDroppedByWatermark"]) for p in query.recentProgress for state in p["stateOperators"])


class EvidenceFold:
    """For foreachBatch: each batch is compared with what lies in the store, by the attributes' classes, and refutations are appended."""

    def __init__(self, store: str, out: str, lhs: list[str], rhs: str):
        self.store, self.out, self.lhs, self.rhs = store, out, lhs, rhs

    def __call__(self, batch: DataFrame, number: int) -> None:
        own = batch.select(*self.lhs, self.rhs).distinct()
        path = f"{self.store}/batch={number}"
        own.write.mode("overwrite").parquet(path)  # a batch run again replaces its own files
        spark = batch.sparkSession
        every = spark.read.parquet(self.store).where(F.col("batch") <= number)
        touched = every.join(spark.read.parquet(path).select(*self.lhs).distinct(), self.lhs, "left_semi")
        watch_fd(touched, self.lhs, self.rhs).write.mode("overwrite").parquet(f"{self.out}/batch={number}")
