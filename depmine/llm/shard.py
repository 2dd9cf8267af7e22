"""Uniform shuffle into shards of exact sizes by a hypergeometric communication matrix.

How many rows source partition p sends to slot range t of a uniform random
permutation is a draw without replacement. The whole matrix need not exist
anywhere: a binary tree over the sources splits the ranges' capacities between
its halves, each node with its own seeded generator, and a task walks from the
root to its source to get its row of the matrix. Rows are permuted in their
source, exchanged by range, and permuted again inside the range. Shards are cut
into ranges of bounded size, so no shard meets in one task.

Defined results: every row gets a place, repeated rows and null or empty texts
too (size 8, checksum 0); an empty table gives an empty result; other columns
are ignored, and a `shard` or `slot` that the input has is replaced. The draw depends on the seed and on how rows lie in source partitions.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import materialize


def hypergeometric(rng: np.random.Generator, good: int, bad: int, take: int) -> int:
    """An exact draw of how many of `take` rows out of good + bad are good, for any size.

    Beyond the generator's range, each side is thinned binomially to about
    `take` rows and the small difference is drawn again without replacement.
    """
    if good + bad < 1_000_000_000:
        return int(rng.hypergeometric(good, bad, take)) if good and take else 0
    if take == 0:
        return 0
    share = take / (good + bad)
    g, b = int(rng.binomial(good, share)), int(rng.binomial(bad, share))
    if g + b > take:
        return g - hypergeometric(rng, g, b, g + b - take)
    return g + hypergeometric(rng, good - g, bad - b, take - g - b) if g + b < take else g


def split(rng: np.random.Generator, capacity: list[int], take: int) -> list[int]:
    """How `take` rows fall on ranges of these free capacities."""
    rest, out = sum(capacity), []
    for c in capacity:
        rest -= c
        got = hypergeometric(rng, c, rest, take)
        out.append(got)
        take -= got
    return out


def matrix_row(ends: list[int], capacity: list[int], source: int, seed: int) -> list[int]:
    """Row `source` of the matrix; ends: running totals of the sources' rows. Every caller sees the same tree."""
    lo, hi = 0, len(ends)
    while hi - lo > 1:
        mid = (lo + hi) // 2
        left = ends[mid - 1] - (ends[lo - 1] if lo else 0)
        rng = np.random.default_rng([seed, lo, hi])
        mine = split(rng, capacity, left)
        if source < mid:
            capacity, hi = mine, mid
        else:
            capacity, lo = [c - m for c, m in zip(capacity, mine)], mid
    return capacity


def slot_ranges(rows: int, shards: int, range_rows: int) -> list[tuple[int, int, int]]:
    """(shard, first slot, size): shard sizes differ by one at most, ranges within a shard too."""
    out = []
    for s in range(shards):
        size = rows // shards + (s < rows % shards)
        parts = max(1, -(-size // range_rows))
        at = 0
        for i in range(parts):
            n = size // parts + (i < size % parts)
            out.append((s, at, n))
            at += n
    return out


def shuffle(df: DataFrame, shards: int = 24, seed: int = 42, range_rows: int = 100_000) -> DataFrame:
    """df with shard and slot: a uniform random permutation cut into shards whose sizes differ by one at most."""
    spark = df.sparkSession
    placed = materialize(df.select(*[c for c in df.columns if c.lower() not in ("shard", "slot")], F.spark_partition_id().alias("__shard_source"), F.monotonically_increasing_id().alias("__shard_place")), "shard-input")
    counts = sorted((r["__shard_source"], r["count"]) for r in placed.groupBy("__shard_source").count().collect())  # a row for each source partition
    sources = {s: i for i, (s, _) in enumerate(counts)}
    ends = np.cumsum([n for _, n in counts]).tolist()
    ranges = slot_ranges(ends[-1] if ends else 0, shards, range_rows)
    held = spark.sparkContext.broadcast((sources, ends, [n for *_, n in ranges]))

    def deal(pdf: pd.DataFrame) -> pd.DataFrame:
        index, totals, capacity = held.value
        source = index[int(pdf["__shard_source"].iloc[0])]
        sends = matrix_row(totals, capacity, source, seed)
        pdf = pdf.sort_values("__shard_place", kind="stable")
        target = np.repeat(np.arange(len(sends)), sends)
        order = np.random.default_rng([seed, 1, source]).permutation(len(pdf))
        out = np.empty(len(pdf), np.int64)
        out[order] = target
        return pd.DataFrame({"__shard_place": pdf["__shard_place"].to_numpy(), "_range": out})

    dealt = placed.select("__shard_source", "__shard_place").groupBy("__shard_source").applyInPandas(deal, "__shard_place long, _range long")
    mixed = Window.partitionBy("_range").orderBy(F.xxhash64("__shard_place", F.lit(seed)), "__shard_place")
    table = spark.createDataFrame([(i, s, a) for i, (s, a, _) in enumerate(ranges)], "_range long, shard int, _first long")
    slots = dealt.withColumn("_turn", F.row_number().over(mixed)).join(table, "_range").select("__shard_place", "shard", (F.col("_first") + F.col("_turn") - 1).alias("slot"))
    return placed.join(slots, "__shard_place").drop("__shard_source", "__shard_place")


def shard_documents(docs: DataFrame, shards: int = 24, seed: int = 42, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard under the law `rows`. Texts are measured before the exchange, so they do not move."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    measured = docs.select(F.col(id_col).alias("doc_id"), (F.octet_length(text).cast("long") + 8).alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"))
    return shuffle(measured, shards, seed).select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
