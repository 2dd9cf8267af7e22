"""SimHash fingerprints linked by multi-index hashing.

Two 64-bit fingerprints within `bits` of each other agree almost fully in one
of a few segments. Each fingerprint is filed under its segment values and under
the values a small Hamming ball around them reaches; fingerprints that share a
file are then compared in full. Only distinct fingerprints are compared, a file
yields the edges of a spanning forest and not its pairs, and a file above
`split_at` is filed anew by its remaining bits until none is, so no group is unbounded.

Defined results: a null or blank text has fingerprint zero, and such texts
link like any others; equal texts share a fingerprint; repeated rows are kept;
a null doc_id takes part but is never a component's id unless all are null; an
empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import binary_list, connected_components, forest, materialize, salted_join, thrifty

WIDTH = 64
BUFFERED = 400_000


def fingerprint(text: bytes | None, shingle: int = 4, seed: int = 42) -> int:
    """The fingerprint of one text, as a signed 64-bit integer."""
    words = (text or b"").lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    size = min(shingle, len(words))
    digest = xxhash.xxh64_intdigest
    hashes = np.array([digest(joined[s:e], seed) for s, e in zip(starts[: len(words) - size + 1].tolist(), ends[size - 1 :].tolist())], np.uint64)
    ones = np.zeros(WIDTH, np.int64)
    for at in range(0, len(hashes), 65_000):
        part = np.unpackbits(hashes[at : at + 65_000].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        ones += part.sum(axis=0, dtype=np.uint32)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view(np.int64)[0])


def fingerprints(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 4) -> DataFrame:
    """(doc_id, fp) for every row."""

    def run(batches):
        for b in batches:
            fps = [fingerprint(t, shingle) for t in binary_list(b.column(1))]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps, pa.int64())], ["doc_id", "fp"])

    return df.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(thrifty(run), "doc_id long, fp long")


def segment_plan(free: int, bits: int, segments: int) -> list[tuple[list[int], int]]:
    """Cut the free bit positions into segments, each with the radius that loses no pair within `bits`.

    With bits = segments * q + rest, a pair that exceeds q in the first rest + 1
    segments and q - 1 in all others would differ in more than `bits`.
    """
    places = [i for i in range(WIDTH) if free >> i & 1]
    q, rest = divmod(bits, segments)
    cut = [len(places) * i // segments for i in range(segments + 1)]
    plan = [(places[cut[i] : cut[i + 1]], q if i <= rest else q - 1) for i in range(segments)]
    return [(p, r) for p, r in plan if r >= 0]


def file_keys(fps: np.ndarray, parents: np.ndarray, free: int, bits: int, segments: int):
    """(key, free, fp) arrays: each fingerprint under every segment value its half-ball reaches.

    Only bits that are zero are raised: two values that differ in at most r
    places both reach their union by at most r raises.
    """
    for number, (places, radius) in enumerate(segment_plan(free, bits, segments)):
        mask = sum(1 << i for i in places)
        base = fps & np.uint64(mask)
        rest = np.array([free & ~mask], np.uint64).view(np.int64)[0]
        salt = np.uint64((number + 1) * 0x9E3779B97F4A7C15 & (1 << 64) - 1)
        for size in range(radius + 1):
            for raised in combinations(places, size):
                up = np.uint64(sum(1 << i for i in raised))
                fit = (base & up) == 0
                key = (base[fit] | up) ^ salt
                for shift, factor in ((33, 0xFF51AFD7ED558CCD), (29, 0xC4CEB9FE1A85EC53)):  # a bijective mix: collisions only add comparisons
                    key = (key ^ (key >> np.uint64(shift))) * np.uint64(factor)
                key = (key ^ (key >> np.uint64(32))) + parents[fit] * np.uint64(0x9FB21C651E98DF25)
                yield key.view(np.int64), np.full(len(key), rest), fps[fit].view(np.int64)


FILED = "key long, free long, fp long"


def file_rows(df: DataFrame, bits: int, segments: int) -> DataFrame:
    """File the rows (key, free, fp) one level deeper."""

    def run(batches):
        for b in batches:
            parents, frees, fps = (b.column(i).to_numpy(zero_copy_only=False).view(np.uint64) for i in range(3))
            for free in np.unique(frees):
                own = frees == free
                for arrays in file_keys(fps[own], parents[own], int(free), bits, segments):
                    yield pa.RecordBatch.from_arrays([pa.array(x) for x in arrays], ["key", "free", "fp"])

    return df.mapInArrow(thrifty(run), FILED)


def spread(fps: np.ndarray, bits: int):
    """Forest edges of one file: breadth first, each fingerprint leaves the unvisited ones once."""
    rest = np.unique(fps)
    while len(rest) > 1:
        queue, rest = [rest[0]], rest[1:]
        while queue and len(rest):
            at = queue.pop()
            near = np.bitwise_count(rest ^ at) <= bits
            if near.any():
                found = rest[near]
                yield np.full(len(found), at), found
                queue.extend(found)
                rest = rest[~near]


def link_files(keys: np.ndarray, fps: np.ndarray, bits: int, small: int = 16):
    """Verified edges within runs of equal keys."""
    edge = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
    sizes = np.diff(np.append(edge, len(keys)))
    few = np.repeat(sizes <= small, sizes)
    k, f = keys[few], fps[few]
    for step in range(1, small):
        if len(k) <= step:
            break
        a, b = f[:-step], f[step:]
        near = (k[:-step] == k[step:]) & (a != b) & (np.bitwise_count(a ^ b) <= bits)
        if near.any():
            yield a[near], b[near]
    for at, n in zip(edge[sizes > small], sizes[sizes > small]):
        yield from spread(fps[at : at + n], bits)


def links(fps: DataFrame, bits: int = 4, segments: int = 3, split_at: int = 20_000) -> DataFrame:
    """Edges (a, b) that connect the same fingerprints as all pairs within `bits` do. fps: distinct values, column fp.

    A file of more than split_at is filed anew by the bits that its key leaves
    free, level by level. Each level settles a third of them, and k free bits
    hold at most 2^k distinct fingerprints, so after four levels no file is large.
    """
    level = file_rows(fps.select(F.lit(0).cast("long").alias("key"), F.lit(-1).cast("long").alias("free"), "fp"), bits, segments)
    parts = []
    while True:
        large = materialize(level.groupBy("key").count().where(F.col("count") > split_at).select("key"), "files")
        if large.isEmpty():
            parts.append(level)
            break
        parts.append(level.join(large, "key", "left_anti"))
        level = file_rows(level.join(large, "key", "left_semi").where("free <> 0").select("key", "free", "fp"), bits, segments)
    filed = parts[0].select("key", "fp")
    for p in parts[1:]:
        filed = filed.unionByName(p.select("key", "fp"))

    def run(batches):
        keys, fps, held, n = np.empty(0, np.int64), np.empty(0, np.uint64), [], 0  # bits are counted on unsigned values

        def flush():
            a, b = forest(*(np.concatenate(x) for x in zip(*held)))
            held.clear()
            return pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], ["a", "b"])

        for b in _closed(batches):
            if b is not None:
                keys = np.concatenate([keys, b.column(0).to_numpy()])
                fps = np.concatenate([fps, b.column(1).to_numpy().view(np.uint64)])
                cut = int(np.searchsorted(keys, keys[-1])) if len(keys) else 0  # the last run may go on
            else:
                cut = len(keys)
            if cut:
                for pair in link_files(keys[:cut], fps[:cut], bits):
                    held.append(pair)
                    n += len(pair[0])
                keys, fps = keys[cut:], fps[cut:]
            if n > BUFFERED:
                yield flush()
                n = 0
        if held:
            yield flush()

    return filed.repartition("key").sortWithinPartitions("key").mapInArrow(thrifty(run), "a long, b long")


def _closed(batches):
    yield from batches
    yield None


def near_duplicates(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 4, bits: int = 4, segments: int = 3) -> DataFrame:
    """(doc_id, fingerprint, component_id, fp) of every row; component_id is the smallest doc_id reachable over links."""
    own = materialize(fingerprints(df, id_col, text_col, shingle), "fingerprints")
    distinct = materialize(own.groupBy("fp").agg(F.min("doc_id").alias("rep")), "distinct")
    roots = connected_components(links(distinct.select("fp"), bits, segments)).withColumnRenamed("node", "fp")
    rooted = distinct.join(roots, "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    lowest = rooted.groupBy("root").agg(F.min("rep").alias("component_id"))
    named = rooted.join(lowest, "root").select("fp", "component_id")
    return salted_join(own, named, "fp", "doc_id", own.count()).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id", "fp")


def keep_one(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows of df that stay: of each component the one with the smallest id (of repeated rows of it, one); rows without id stay."""
    return keep_lowest(df, near_duplicates(df, id_col, text_col, **options), id_col)


def keep_lowest(df: DataFrame, classes: DataFrame, id_col: str) -> DataFrame:
    """The rows of df whose id is the component_id of their class, each id once, and the rows without id."""
    stay = classes.where("doc_id = component_id").groupBy("doc_id").agg(F.count("*").alias("__rows")).withColumnRenamed("doc_id", id_col)
    kept = df.join(stay, id_col)
    single = kept.where(F.col("__rows") == 1).drop("__rows")
    repeated = kept.where(F.col("__rows") > 1).drop("__rows").dropDuplicates([id_col])
    return single.unionByName(repeated).unionByName(df.where(F.col(id_col).isNull()).select(*single.columns))
