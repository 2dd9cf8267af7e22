"""Reading and writing relations, results and streams."""

from __future__ import annotations

import re
import uuid

from pyspark.sql import DataFrame, SparkSession

FORMATS = ("parquet", "csv", "json", "text", "orc")


def load(spark: SparkSession, what, format: str = "parquet", schema=None, columns=None, **options) -> DataFrame:
    """A path, a table name (format `table`), SQL text (`sql`) or rows in memory (`rows`). Parquet and ORC bring their schema; csv and json take one."""
    if format == "sql":
        df = spark.sql(what)
    elif format == "table":
        df = spark.table(what)
    elif format == "rows":
        df = spark.createDataFrame(what, schema)
    elif format in FORMATS:
        reader = spark.read.options(**options)
        df = (reader.schema(schema) if schema else reader).format(format).load(what)
    else:
        raise ValueError(f"unknown format {format}")
    return df.select(*columns) if columns else df


def save(df: DataFrame, path: str, format: str = "parquet", mode: str = "overwrite", partition_by=()) -> str:
    df.write.mode(mode).format(format).partitionBy(*partition_by).save(path)
    return path


def view(df: DataFrame, name: str) -> DataFrame:
    df.createOrReplaceTempView(name)
    return df


def load_stream(spark: SparkSession, path: str, schema, format: str = "parquet", **options) -> DataFrame:
    return spark.readStream.schema(schema).options(**options).format(format).load(path)


def write_stream(df: DataFrame, checkpoint: str, batch=None, format: str = "memory", name: str | None = None, mode: str = "append"):
    """A started query: to a sink, or to a function of (batch, number)."""
    writer = df.writeStream.outputMode(mode).option("checkpointLocation", checkpoint)
    writer = writer.foreachBatch(batch) if batch else writer.format(format)
    return (writer.queryName(name) if name else writer).start()


#: Used only on one machine whose session names no spark.checkpoint.dir, as in tests.
LOCAL_FALLBACK = "/tmp/checkpoints/depmine"


def shared_dir(spark: SparkSession) -> str:
    """The folder that the driver and all executors share; on a cluster the session must name it."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not named and not re.match(r"local($|\[)", spark.sparkContext.master):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return (named or LOCAL_FALLBACK).rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def drop_path(spark: SparkSession, path: str) -> None:
    """Delete a folder of the shared storage through Spark's own file system layer."""
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def release(spark: SparkSession) -> None:
    """Let the shuffle files of finished jobs go: Spark deletes them once the driver's JVM has collected their plans."""
    spark.sparkContext._jvm.System.gc()


def stored(df: DataFrame, name: str, partition_by=()) -> tuple[DataFrame, str]:
    """df written to the shared folder and read back, and its path, for drop_path once it is used up."""
    spark = df.sparkSession
    path = fresh_path(spark, name)
    df.write.partitionBy(*partition_by).parquet(path)
    return spark.read.schema(df.schema).parquet(path).select(*df.columns), path


def materialize(df: DataFrame, name: str = "level") -> DataFrame:
    """Cut the lineage of an iteration and fix row numbers: df written to the shared folder and read back.

    Unlike a cache, the copy survives the loss of executors.
    """
    return stored(df, name)[0]
