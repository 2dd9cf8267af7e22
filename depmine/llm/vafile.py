"""Exact top-k search by inner product over a vector-approximation file.

The file has two tables: small cells of every vector, one signed byte a
component, and the exact vectors. A search scans the cells alone: since all
cells have one width, the lower and upper bound of a score differ from the
product of the query with the cells' lower corners by two constants of the
query. A vector whose upper bound stays under the running kth best lower bound
is out. Of the survivors, the k with the best bounds are read in full first;
then those whose bound still reaches the kth exact score so far, and no others.

Queries come in blocks of bounded size, which are the only thing broadcast, and
each block is a job of its own. Cell width and first thresholds come from a
bounded sample of vectors, which only sharpens bounds and never decides: a
vector with a component beyond the cells is always read in full.

Defined results: vectors that are null, empty or hold null or non-finite
components take no part; vectors of other lengths are compared over the common
prefix; repeated ids are each a candidate, but a query is answered once for
each id (by its greatest vector) and never meets rows of its own id; ties go to the smaller id; an
empty table gives an empty result. Scores are exact 64-bit integers; a score
beyond them is an error.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import fresh_path, materialize

RESULT = "query_id long, vec_id long, score long"
CELL = 127


def exact_vectors(df: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", scale: int = 1024) -> DataFrame:
    """(row, vec_id, exact array<long>) of the vectors that take part; row tells repeated ids apart."""
    floored = F.transform(F.col(vector_col), lambda x: F.floor(x.cast("double") * scale))
    whole = ~F.exists(F.col(vector_col), lambda x: x.isNull() | F.isnan(x) | (F.abs(x.cast("double")) == F.lit(float("inf"))))
    rows = df.where(F.col(id_col).isNotNull() & F.col(vector_col).isNotNull() & (F.size(vector_col) > 0)).where(whole)
    return rows.select(F.monotonically_increasing_id().alias("row"), F.col(id_col).cast("long").alias("vec_id"), floored.alias("exact"))


def cells_of(exact: DataFrame, width: int) -> DataFrame:
    """(row, vec_id, cells): each component's cell as a byte; -128 stands for one beyond the cells."""

    def run(batches):
        for b in batches:
            cells = []
            for v in b.column(2).to_pylist():
                c = np.array(v, np.int64) // width
                cells.append(np.where(np.abs(c) > CELL, -128, c).astype(np.int8).tobytes())
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(cells, pa.binary())], ["row", "vec_id", "cells"])

    return exact.mapInArrow(run, "row long, vec_id long, cells binary")


def _lists(column: pa.Array, dims: int) -> np.ndarray:
    lengths = np.diff(column.offsets.to_numpy())
    if len(lengths) and (lengths == dims).all():
        return column.flatten().to_numpy().reshape(-1, dims)
    out = np.zeros((len(column), dims), np.int64)
    for i, v in enumerate(column.to_pylist()):
        out[i, : min(dims, len(v))] = v[:dims]
    return out


def _cells(column: pa.Array, dims: int) -> np.ndarray:
    raw = column.to_pylist()
    if all(len(x) == dims for x in raw):
        return np.frombuffer(b"".join(raw), np.int8).reshape(-1, dims).astype(np.float64)
    out = np.zeros((len(raw), dims))
    for i, x in enumerate(raw):
        v = np.frombuffer(x, np.int8)[:dims]
        out[i, : len(v)] = v
    return out


def products(vectors: np.ndarray, query: np.ndarray) -> np.ndarray:
    """Exact integer inner products: in floating point where every partial sum fits 53 bits, else in whole numbers."""
    most = float(np.abs(vectors).max(initial=0)) * float(np.abs(query).astype(np.float64).sum())
    if most < 2**53:
        return (vectors.astype(np.float64) @ query.astype(np.float64)).astype(np.int64)
    if most < 2**63:
        return vectors @ query
    out = [sum(int(a) * int(b) for a, b in zip(v, query)) for v in vectors.tolist()]
    if any(not -(2**63) <= x < 2**63 for x in out):
        raise OverflowError("a score exceeds 64 bits")
    return np.array(out, np.int64)


class Block:
    """A block of queries with what bounds need: ids, vectors, and for each a score that at least k others reach."""

    def __init__(self, own: pa.Table, sample: pa.Table, k: int, width: int):
        lists = own.column("exact").to_pylist()
        self.k, self.width, self.dims = k, width, max(map(len, lists))
        self.ids = own.column("vec_id").to_numpy()
        self.vectors = _lists(own.column("exact").combine_chunks(), self.dims)
        near, near_ids = _lists(sample.column("exact").combine_chunks(), self.dims), sample.column("vec_id").to_numpy()
        self.least = np.full(len(self.ids), -np.inf)
        q = self.vectors.astype(np.float64)
        for i, v in enumerate(self.vectors):
            scores = products(near, v)[near_ids != self.ids[i]]
            if len(scores) >= k:
                self.least[i] = np.partition(scores, -k)[-k]
        slack = np.abs(q).sum(axis=1) * (CELL + 1) * width * 2.0**-40  # more than rounding can take
        self.above = (width - 1) * np.maximum(q, 0).sum(axis=1) + slack
        self.below = (width - 1) * np.minimum(q, 0).sum(axis=1) - slack
        self.q = q

    def scan(self, batches):
        """(query, row, upper): the vectors that may be among the k best, by their cells alone."""
        floor = self.least - np.abs(self.least) * 2.0**-40
        for b in batches:
            ids = b.column(1).to_numpy()
            cells = _cells(b.column(2), self.dims)
            beyond = (cells == -128).any(axis=1)
            found = [[], [], []]
            for at in range(0, len(self.ids), 256):
                base = (self.q[at : at + 256] @ cells.T) * self.width
                for i, corner in enumerate(base, start=at):
                    upper = np.where(beyond, np.inf, corner + self.above[i])
                    lower = np.where(beyond, -np.inf, corner + self.below[i])
                    upper[ids == self.ids[i]] = lower[ids == self.ids[i]] = -np.inf
                    if len(lower) > self.k:
                        floor[i] = max(floor[i], np.partition(lower, -self.k)[-self.k])
                    left = np.flatnonzero((upper >= floor[i]) & (upper > -np.inf))
                    found[0].append(np.full(len(left), i))
                    found[1].append(left)
                    found[2].append(upper[left])
            rows = b.column(0).to_numpy()
            query, place, upper = (np.concatenate(x) for x in found)
            yield pa.RecordBatch.from_arrays([pa.array(query.astype(np.int32)), pa.array(rows[place]), pa.array(upper)], ["query", "row", "upper"])

    def score(self, batches):
        """(query_id, vec_id, score, query) of the vectors read in full, each with the numbers of the queries it is read for."""
        for b in batches:
            vectors = _lists(b.column(1), self.dims)
            lists = b.column(2)
            place = np.repeat(np.arange(len(lists)), np.diff(lists.offsets.to_numpy()))
            query = lists.flatten().to_numpy()
            scores = np.empty(len(query), np.int64)
            for i in np.unique(query):
                at = np.flatnonzero(query == i)
                scores[at] = products(vectors[place[at]], self.vectors[i])
            ids = b.column(0).to_numpy()
            yield pa.RecordBatch.from_arrays([pa.array(self.ids[query]), pa.array(ids[place]), pa.array(scores), pa.array(query.astype(np.int32))], ["query_id", "vec_id", "score", "query"])


def search(df: DataFrame, is_query, k: int = 10, id_col: str = "vec_id", vector_col: str = "embedding", scale: int = 1024, query_bytes: int = 32 << 20, seeds: int = 2_048) -> DataFrame:
    """(query_id, rank, vec_id, score): the k highest integer inner products of each query.

    is_query: a column over vec_id. query_bytes bounds what a broadcast holds,
    seeds the sample that cell width and thresholds start from.
    """
    spark = df.sparkSession
    exact = materialize(exact_vectors(df, id_col, vector_col, scale), "exact")
    sample = exact.select("vec_id", "exact", F.xxhash64("vec_id").alias("h")).orderBy("h").limit(seeds).toArrow()
    largest = np.sort(np.abs(sample.column("exact").combine_chunks().flatten().to_numpy()).astype(np.float64)) if sample.num_rows else np.zeros(1)
    width = 1
    while width * CELL < largest[int(len(largest) * 0.9999) - 1 if len(largest) > 1 else 0] * 1.5:
        width *= 2
    cells = materialize(cells_of(exact, width), "cells")
    queries = exact.where(is_query).groupBy("vec_id").agg(F.max("exact").alias("exact"))
    stat = queries.agg(F.count("*").alias("n"), F.sum(F.size("exact")).alias("c")).first()
    blocks = max(1, -(-2 * 8 * (stat["c"] or 0) // query_bytes))
    path = fresh_path(spark, "found")
    for block in range(blocks if stat["n"] else 0):
        own = queries.where(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)) == block).toArrow()
        if own.num_rows:
            _answer(cells, exact, spark.sparkContext.broadcast(Block(own, sample, k, width)), k).write.parquet(f"{path}/block={block}")
    if not stat["n"]:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    return spark.read.schema("query_id long, rank int, vec_id long, score long").parquet(path).select("query_id", "rank", "vec_id", "score")


def _answer(cells: DataFrame, exact: DataFrame, held, k: int) -> DataFrame:
    survivors = materialize(cells.mapInArrow(lambda batches: held.value.scan(batches), "query int, row long, upper double"), "survivors")
    best = Window.partitionBy("query").orderBy(F.desc("upper"), "row")

    def read(wanted: DataFrame) -> DataFrame:
        """Exact scores: each vector is fetched once, with the queries that want it."""
        asked = wanted.groupBy("row").agg(F.collect_list("query").alias("queries"))  # at most a block of queries each
        rows = exact.join(asked, "row").select("vec_id", "exact", "queries")
        return rows.mapInArrow(lambda batches: held.value.score(batches), f"{RESULT}, query int")

    first = survivors.withColumn("turn", F.row_number().over(best)).where(F.col("turn") <= k)
    read_first = materialize(read(first), "read")
    certain = read_first.groupBy("query").agg(F.when(F.count("*") >= k, F.min("score")).alias("least"))
    rest = survivors.join(F.broadcast(certain), "query").where(F.col("least").isNull() | (F.col("upper") >= F.col("least"))).join(first.select("query", "row"), ["query", "row"], "left_anti")
    found = read_first.unionByName(read(rest))
    ranked = found.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), F.asc("vec_id"))))
    return ranked.where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
