"""Shared helpers of the training-data operators: joins that split hot keys, component labels, folds."""

from __future__ import annotations

import contextlib
import ctypes

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from depmine.sources.io import drop_path, fresh_path, materialize, stored

__all__ = ["binary_list", "connected_components", "drop_path", "fold", "forest", "fresh_path", "give_back", "materialize", "salted_join", "short_batches", "stored", "thrifty"]

#: Most bytes of rows that Spark hands to a Python worker at once where short_batches() was called.
BATCH_BYTES = 4 << 20


def short_batches(spark: SparkSession) -> None:
    """Set the session's limit on the bytes of an Arrow batch: 10,000 whole texts in one batch are held several times over, in the executor and in its Python worker."""
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))


def give_back() -> None:
    """Return freed memory to the system, which a process that waits for its next task would keep."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # only glibc has it
        ctypes.CDLL(None).malloc_trim(0)


def thrifty(run):
    """run(batches), a function for mapInArrow, that gives memory back at the end of each task."""

    def whole(batches):
        try:
            yield from run(batches)
        finally:
            give_back()

    return whole


def binary_list(column: pa.Array) -> list[bytes | None]:
    """UTF-8 bytes of each value of an Arrow string column."""
    kind = pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()
    return column.cast(kind).to_pylist()


def fold(doc_id, modulus: int):
    """crc32 of the id as text (null: of the empty text), modulo."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % modulus


def forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Star edges (node, smallest node of its component) of a bounded edge list; roots have none."""
    nodes, inverse = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = inverse[: len(a)], inverse[len(a) :]
    label = np.arange(len(nodes))
    while True:
        low = np.minimum(label[x], label[y])
        new = label.copy()
        for end in (x, y, label[x], label[y]):
            np.minimum.at(new, end, low)
        while not np.array_equal(jumped := new[new], new):
            new = jumped
        if np.array_equal(new, label):
            break
        label = new
    moved = label != np.arange(len(nodes))
    return nodes[moved], nodes[label[moved]]


def salted_join(rows: DataFrame, table: DataFrame, key: str, by: str, n: int) -> DataFrame:
    """Inner join of `rows` with a table in which `key` is unique, where a key may hold any share of the n rows.

    A key with more than a thousandth of the rows is cut by a hash of `by` into
    parts of about that size, and its row of the table is sent to each part. The
    list of these keys, at most a thousand, is told to all tasks.
    """
    if n <= 10_000:  # no key can be hot
        return rows.join(table, key)
    most = max(200, n // 1_000)
    hot = rows.groupBy(key).agg(F.count("*").alias("__n")).where(F.col("__n") > most).select(F.col(key).alias("__key"), F.ceil(F.col("__n") / most).cast("int").alias("__salts"))
    marked = rows.join(F.broadcast(hot), F.col(key) == F.col("__key"), "left").withColumn("__salt", F.coalesce(F.pmod(F.xxhash64(by), F.col("__salts")), F.lit(0)).cast("int")).drop("__key", "__salts")
    spread = table.join(F.broadcast(hot), F.col(key) == F.col("__key"), "left").withColumn("__salt", F.explode(F.sequence(F.lit(0), F.coalesce("__salts", F.lit(1)) - 1))).drop("__key", "__salts")
    return marked.join(spread, [key, "__salt"]).drop("__salt")


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, root) for every node of the undirected edges (a, b): root is the component's smallest node.

    Alternates two local rewirings until nothing changes: every node hands its
    larger neighbours to the smallest one it sees, then keeps one link
    downwards. A node with many neighbours is split over tasks. Each round is
    written to shared storage, so no lineage grows, and the round before is
    deleted; nothing but counts reaches the driver.
    """
    spark = edges.sparkSession
    current, path = stored(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    n = current.count()
    for _ in range(max_rounds if n else 0):
        both = current.unionByName(current.select(F.col("b").alias("a"), F.col("a").alias("b")))
        lowest = both.groupBy("a").agg(F.min("b").alias("low")).select("a", F.least("a", "low").alias("low"))
        large = salted_join(both, lowest, "a", "b", n).where("b > a").select(F.col("b").alias("a"), F.col("low").alias("b")).where("a <> b").distinct()
        down = salted_join(large, large.groupBy("a").agg(F.min("b").alias("low")), "a", "b", n)
        small = down.select(F.when(F.col("b") == F.col("low"), F.col("a")).otherwise(F.col("b")).alias("a"), F.col("low").alias("b")).union(down.select("a", F.col("low").alias("b")))
        after, written = stored(small.where("a <> b").distinct(), "edges")
        left = after.count()
        same = left == n and after.join(current, ["a", "b"], "left_anti").isEmpty()
        drop_path(spark, path)
        current, path, n = after, written, left
        if same:
            break
    else:
        if n:
            raise RuntimeError("the components did not settle")
    return current.select(F.col("a").alias("node"), F.col("b").alias("root"))
