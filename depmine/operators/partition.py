"""Classes of equal rows: membership tables, and class counts of many attribute sets at once.

Values are compared by their own types: a class never depends on how a value
is printed, -0.0 equals 0.0, NaN equals NaN and null equals null.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from depmine.functions.bits import members
from depmine.functions.prep import cells
from depmine.sources.io import materialize, release, stored

from .distribute import candidates_deal

#: Attribute sets of one job: bounds how often a row is expanded.
BATCH = 32
#: Rows of one exchange of fingerprints; shuffle files of one exchange go before the next.
EXCHANGE_ROWS = 120_000_000
#: A class above a thousandth of all rows, or this many, is looked up by broadcast; there are at most a thousand of them for each key column.
HOT_SHARE, HOT_ROWS = 1_000, 100_000


def numbered(rows: DataFrame, keys: list[str], row_id: str, n: int | None = None) -> DataFrame:
    """rows with class_id: the smallest row of those equal on keys, which needs no global numbering.

    The members of a large class are named by a broadcast of the few large
    classes (their number is bounded by rows / size), so no task receives a
    whole one; all others by an exchange. Tables smaller than a large class take one window.
    """
    n = rows.count() if n is None else n
    least = max(HOT_ROWS, n // HOT_SHARE)
    if n <= least:
        return rows.withColumn("class_id", F.min(row_id).over(Window.partitionBy(*keys)))
    short = [f"_k{i}" for i in range(len(keys))]
    sizes = rows.groupBy(*[F.col(k).alias(s) for k, s in zip(keys, short)]).agg(F.min(row_id).alias("class_id"), F.count("*").alias("_size"))
    met = reduce(lambda a, b: a & b, [F.col(k).eqNullSafe(F.col(s)) for k, s in zip(keys, short)])
    large = sizes.where(F.col("_size") > least)
    marked = rows.join(F.broadcast(large), met, "left").select(*rows.columns, "class_id")
    rest = marked.where("class_id is null").drop("class_id").join(sizes.where(F.col("_size") <= least), met)
    return rest.select(*rows.columns, "class_id").unionByName(marked.where("class_id is not null"))


def classes_from_rows(df: DataFrame, attrs: list[str], row_id: str) -> DataFrame:
    """(class_id, row_id) of one attribute set."""
    rows = df.select(*attrs, F.col(row_id).alias("__row"))
    return numbered(rows, attrs, "__row").select("class_id", F.col("__row").alias("row_id"))


def column_classes(df: DataFrame, attrs: list[str], row_id: str, n: int | None = None) -> DataFrame:
    """(node, class_id, row_id) of every single column; node is the column's number. Columns are dealt out as rows, then grouped."""
    values, slots = cells(df, attrs)
    flat = df.select(F.col(row_id).alias("row_id"), F.explode(values).alias("c")).select("row_id", F.col("c.attr").alias("node"), *[f"c.{s}" for s in slots])
    n = (df.count() if n is None else n) * len(attrs)
    return numbered(flat, ["node", *slots], "row_id", n).select("node", "class_id", "row_id")


def intersect(pi: DataFrame, parents: DataFrame, n: int | None = None, hint: str | None = None) -> DataFrame:
    """Classes of new sets from two stored parents each. pi: (node, class_id, row_id); parents: (node, left, right), a level's candidates, checked by the caller."""
    few = F.broadcast(parents) if hint is None else parents.hint(hint)
    left = pi.select(F.col("node").alias("left"), F.col("class_id").alias("l_class"), "row_id").join(few, "left")
    right = pi.select(F.col("node").alias("right"), F.col("class_id").alias("r_class"), "row_id")
    rows = left.join(right if hint is None else right.hint(hint), ["right", "row_id"]).select("node", "l_class", "r_class", "row_id")
    return numbered(rows, ["node", "l_class", "r_class"], "row_id", n).select("node", "class_id", "row_id")


def _tuple(df: DataFrame, attrs: list[str], mask: int):
    return [F.col(attrs[i]) for i in members(mask)]


def class_sizes(df: DataFrame, attrs: list[str], masks: list[int]) -> dict[int, tuple[int, int]]:
    """(classes, rows of the largest) of each attribute set; one exchange for each batch of sets."""
    out = {}
    for at in range(0, len(masks), BATCH):
        batch = masks[at : at + BATCH]
        union = 0
        for m in batch:
            union |= m
        used = members(union)
        sets = [[F.col(attrs[i]) for i in members(m)] for m in batch]
        classes = df.groupingSets(sets, *[F.col(attrs[i]) for i in used]).agg(F.grouping_id().alias("gid"), F.count("*").alias("size"))
        named = {sum(1 << (len(used) - 1 - p) for p, i in enumerate(used) if not m >> i & 1): m for m in batch}
        rows = classes.groupBy("gid").agg(F.count("*").alias("n"), F.max("size").alias("most")).collect()  # a row for each set
        out |= {named[r["gid"]]: (r["n"], r["most"]) for r in rows}
    return {m: out.get(m, (0, 0)) for m in masks}


def counts_by_grouping_sets(df: DataFrame, attrs: list[str], masks: list[int]) -> dict[int, int]:
    """Exact: one exchange for each batch of attribute sets."""
    return {m: n for m, (n, _) in class_sizes(df, attrs, masks).items()}


def counts_one_by_one(df: DataFrame, attrs: list[str], masks: list[int]) -> dict[int, int]:
    """One grouping for each attribute set, as the scarce-memory rescan plan has it."""
    return {m: df.select(*_tuple(df, attrs, m)).distinct().count() if m else min(1, df.limit(1).count()) for m in masks}


def counts_by_fingerprint(df: DataFrame, attrs: list[str], masks: list[int]) -> dict[int, int]:
    """Rows of an exchange are a set's number and two 64-bit hashes, however wide the attributes. For ranking and very wide keys; equal up to hash collisions."""
    out = {}
    size = max(1, min(BATCH, EXCHANGE_ROWS // max(1, df.count())))
    for at in range(0, len(masks), size):
        batch = masks[at : at + size]
        prints = [F.struct(F.lit(n).alias("set"), F.xxhash64(F.lit(1), *_tuple(df, attrs, m), *[F.isnull(c) for c in _tuple(df, attrs, m)]).alias("a"), F.xxhash64(F.lit(2), *_tuple(df, attrs, m)).alias("b")) for n, m in enumerate(batch)]
        rows = df.select(F.explode(F.array(*prints)).alias("p")).select("p.*").distinct().groupBy("set").agg(F.count("*").alias("n")).collect()
        out |= {batch[r["set"]]: r["n"] for r in rows}
        if size < BATCH:
            release(df.sparkSession)
    return {m: out.get(m, 0) for m in masks}


#: Bytes of a value on its way to the driver, by type; texts and binaries by their length.
_WIDTH = {"tinyint": 1, "smallint": 2, "int": 4, "float": 4, "boolean": 1, "date": 4}


def raw_bytes(df: DataFrame, attrs: list[str]) -> tuple[int, int]:
    """(rows, bytes of the values as they would reach the driver), counted in one pass."""
    fixed, texts = 0, []
    for a in attrs:
        kind = df.schema[a].dataType
        if isinstance(kind, (T.StringType, T.BinaryType)):
            texts.append(F.octet_length(F.col(a)))
        elif isinstance(kind, (T.ArrayType, T.MapType, T.StructType)):
            texts.append(F.octet_length(F.to_json(F.struct(F.col(a)))))
        else:
            fixed += _WIDTH.get(kind.simpleString(), 8)
    long = reduce(lambda a, b: a + b, [F.coalesce(x.cast("long"), F.lit(0)) + 4 for x in texts], F.lit(0).cast("long"))
    row = df.agg(F.count("*").alias("n"), F.coalesce(F.sum(long), F.lit(0)).alias("b")).first()
    return row["n"], row["n"] * fixed + row["b"]


class BroadcastCodes:
    """The resident rescan plan: one broadcast copy of the encoded relation, candidates dealt to `k` tasks.

    Refuses a relation whose values or codes exceed `limit` bytes, before any of
    them moves: that is what the scarce-memory plans are for. Codes keep the
    order of values, nulls first, NaN last.
    """

    def __init__(self, df: DataFrame, attrs: list[str], k: int, limit: int = 512 << 20):
        self.spark, self.k, self.attrs = df.sparkSession, k, attrs
        self.rows, raw = raw_bytes(df, attrs)
        if max(raw, 4 * self.rows * len(attrs)) > limit:
            raise MemoryError(f"{raw} bytes of values, {4 * self.rows * len(attrs)} of codes: more than the limit of {limit}; use memory='spill'")
        codes = encode(df.select(*attrs).toArrow())
        self.bytes = sum(c.nbytes for c, _ in codes)
        self.held = self.spark.sparkContext.broadcast(codes)

    def counts(self, masks: list[int]) -> dict[int, int]:
        return {m: n for m, n in zip(masks, self.answer(masks, lambda codes, m: count_distinct(codes, m)))}

    def answer(self, questions: list, ask) -> list[int]:
        """ask(codes, question) for each question, dealt round robin to k tasks; an integer each."""
        if not questions:
            return []
        held = self.held
        texts = candidates_deal([(i, repr(q)) for i, q in enumerate(questions)], min(self.k, len(questions)))  # as text: a mask may be wider than any integer column

        def run(batches):
            import ast

            for pdf in batches:
                yield pd.DataFrame({"at": pdf["at"], "n": [int(ask(held.value, ast.literal_eval(q))) for q in pdf["question"]]})

        deal = self.spark.sparkContext.parallelize([x for own in texts for x in own], len(texts)).toDF("at int, question string")
        got = {r["at"]: r["n"] for r in deal.mapInPandas(run, "at int, n long").collect()}  # a row for each question
        return [got[i] for i in range(len(questions))]

    def inspect(self, asked: dict[int, int]) -> tuple[dict[int, int], np.ndarray]:
        """What holds of the bits asked of each set, and agreements of rows (see inspected)."""
        held, masks = self.held, list(asked)
        deal = self.spark.createDataFrame([(i, x, asked[x]) for i, x in enumerate(masks)], "at int, mask long, asked long").repartition(min(self.k, len(masks)))

        def run(batches):
            for b in batches:
                yield answers(b.column(0).to_pylist(), [inspected(held.value, x, bits) for x, bits in zip(b.column(1).to_pylist(), b.column(2).to_pylist())])

        got = deal.mapInArrow(run, ANSWERS).collect()  # a row for each set
        return {masks[r["at"]]: r["held"] for r in got}, gathered(got)


#: A relation of more rows is counted in parts; about so many rows or bytes make a part, and a task refuses a part of more than the last two.
DEALT_ROWS, PART_ROWS, PART_BYTES, MOST_ROWS, MOST_BYTES = 500_000, 250_000, 64 << 20, 2_000_000, 512 << 20
_PLAIN = (T.ByteType, T.ShortType, T.IntegerType, T.LongType, T.FloatType, T.DoubleType, T.DateType, T.TimestampType, T.TimestampNTZType, T.DecimalType, T.BinaryType)


def dealable(df: DataFrame, attrs: list[str]) -> bool:
    """Whether codes of the values in a task tell what Spark's grouping tells: no nested types, no collations."""
    return all(isinstance(k := df.schema[a].dataType, _PLAIN) or k.simpleString() == "string" for a in attrs)


class DealtCodes:
    """The spilling rescan plan of a large relation: rows are dealt by the value of one attribute, so that no class of a set with this attribute spans two parts, and each part is kept as codes in shared storage.

    One exchange of the rows serves all attribute sets with the attribute, at
    every level; their counts are sums over parts and move nothing. Attributes
    with too few values, or with one too frequent for a task, deal nothing: sets of such
    alone are counted by grouping sets on the distinct rows of these attributes.
    """

    def __init__(self, df: DataFrame, attrs: list[str], k: int):
        self.spark, self.attrs, self.k, self.sample = df.sparkSession, attrs, k, None
        joined = "Join" in df._jdf.queryExecution().optimizedPlan().toString()
        self.df = materialize(df.select(*attrs), "relation") if joined else df.select(*attrs)
        self.rows, self.raw = raw_bytes(self.df, attrs)
        self.parts = max(k, -(-self.rows // PART_ROWS), -(-self.raw // PART_BYTES))
        seen = self.df.agg(*[F.approx_count_distinct(a).alias(f"n{i}") for i, a in enumerate(attrs)]).first()
        self.dealers = sorted((i for i in range(len(attrs)) if seen[i] >= 4 * self.parts), key=lambda i: -seen[i])
        self.kept: dict[int, tuple[list[int], DataFrame]] = {}
        self.rest: tuple[int, DataFrame] | None = None

    def counts(self, masks: list[int]) -> dict[int, int]:
        out = {0: min(1, self.rows)}
        left = [m for m in masks if m]
        for at in list(self.dealers):
            own = [m for m in left if m >> at & 1]
            if own and (parts := self._parts(at, reduce(lambda a, b: a | b, own))) is None:
                self.dealers.remove(at)
            elif own:
                out |= self._counted(*parts, own)
                left = [m for m in left if not m >> at & 1]
        if left:
            out |= counts_by_grouping_sets(self._few(left), self.attrs, left)
        return {m: out.get(m, 0) for m in masks}

    def _few(self, masks: list[int]) -> DataFrame:
        """The distinct rows of the attributes that deal nothing: what sets of such alone can tell apart."""
        union = reduce(lambda a, b: a | b, masks) | sum(1 << i for i in range(len(self.attrs)) if i not in self.dealers)
        if self.rest is None or self.rest[0] != union:
            self.rest = union, materialize(self.df.select(*[self.attrs[i] for i in members(union)]).distinct(), "few")
            release(self.spark)
        return self.rest[1]

    def _parts(self, at: int, union: int) -> tuple[list[int], DataFrame] | None:
        """The columns kept, and (rows, sizes, c0, c1, ...): a row for each part, the codes of a column in one value; None if a part is too large for a task.

        Sets with an earlier dealer are counted there, so later ones do not keep its column."""
        if at not in self.kept or not set(members(union)) <= set(self.kept[at][0]):
            earlier = self.dealers[: self.dealers.index(at)]
            held = [i for i in range(len(self.attrs)) if i not in earlier or union >> i & 1]
            columns, width = [self.attrs[i] for i in held], len(held)
            names = ["rows", "sizes", *[f"c{i}" for i in held]]
            kinds = [pa.int64(), pa.list_(pa.int64()), *[pa.binary()] * width]

            def pack(batches):
                held, rows, size = [], 0, 0
                for b in batches:
                    rows, size = rows + b.num_rows, size + b.nbytes
                    held = [*held, b] if held is not None and rows <= MOST_ROWS and size <= MOST_BYTES else None
                if held is None:
                    yield pa.RecordBatch.from_arrays([pa.array([x], k) for x, k in zip([rows, None, *[None] * width], kinds)], names)
                elif rows:
                    codes = encode(pa.Table.from_batches(held))
                    cells = [c.astype(np.uint8 if own <= 1 << 8 else np.uint16 if own <= 1 << 16 else np.int32).tobytes() for c, own in codes]
                    yield pa.RecordBatch.from_arrays([pa.array([x], k) for x, k in zip([rows, [own for _, own in codes], *cells], kinds)], names)

            dealt = self.df.select(*columns).repartition(self.parts, self.attrs[at]).mapInArrow(pack, "rows long, sizes array<long>, " + ", ".join(f"c{i} binary" for i in held))
            made = materialize(dealt, "parts")
            release(self.spark)
            if not made.where("sizes is null").isEmpty():
                return None
            self.kept[at] = held, made
        return self.kept[at]

    def _counted(self, held: list[int], parts: DataFrame, masks: list[int]) -> dict[int, int]:
        used = members(reduce(lambda a, b: a | b, masks))
        place = [held.index(i) for i in used]
        asked = [sum(1 << p for p, i in enumerate(used) if m >> i & 1) for m in masks]

        def run(batches):
            for b in batches:
                for rows, sizes, *cells in zip(*[c.to_pylist() for c in b.columns]):
                    codes = [(np.frombuffer(c, {1: np.uint8, 2: np.uint16, 4: np.int32}[len(c) // rows]), sizes[i]) for i, c in zip(place, cells)]
                    found = [count_distinct(codes, m) for m in asked]
                    yield pa.RecordBatch.from_arrays([pa.array(range(len(asked)), pa.int32()), pa.array(found, pa.int64())], ["at", "n"])

        each = parts.select("rows", "sizes", *[f"c{i}" for i in used]).mapInArrow(run, "at int, n long")
        got = each.groupBy("at").agg(F.sum("n").alias("n")).collect()  # a row for each set
        return {masks[r["at"]]: r["n"] for r in got}

    def sampled(self) -> BroadcastCodes:
        """The codes of about a part's rows, dealt by their hash: what these refute is refuted; what they do not is left to inspect()."""
        if self.sample is None:
            share = max(1, self.rows // PART_ROWS, self.raw // PART_BYTES)
            self.sample = BroadcastCodes(self.df.where(F.pmod(F.xxhash64(*self.attrs), F.lit(share)) == 0), self.attrs, self.k)
        return self.sample

    def inspect(self, asked: dict[int, int]) -> tuple[dict[int, int], np.ndarray]:
        """What holds of the bits asked of each set, and agreements of rows (see inspected)."""
        out, found, left, everything = {}, [np.empty(0, np.int64)], dict(asked), (1 << len(self.attrs)) - 1
        for at in list(self.dealers):
            own = {x: bits for x, bits in left.items() if x >> at & 1}
            if own and (parts := self._parts(at, everything)) is None:
                self.dealers.remove(at)
            elif own:
                answer, pairs = self._inspected(*parts, own)
                out |= answer
                found.append(pairs)
                left = {x: bits for x, bits in left.items() if not x >> at & 1}
        if left:
            wanted = {y for x, bits in left.items() for y in (x, *[x | 1 << a for a in members(bits & everything)])}
            n = self.counts(sorted(wanted))
            for x, bits in left.items():
                out[x] = sum(1 << a for a in members(bits & everything) if n[x] == n[x | 1 << a]) | (bits & ~everything if n[x] == self.rows else 0)
        return out, np.unique(np.concatenate(found))

    def _inspected(self, held: list[int], parts: DataFrame, asked: dict[int, int]) -> tuple[dict[int, int], np.ndarray]:
        masks = list(asked)
        told = self.spark.sparkContext.broadcast((masks, list(asked.values())))

        def run(batches):
            for b in batches:
                for rows, sizes, *cells in zip(*[c.to_pylist() for c in b.columns]):
                    codes = [(np.frombuffer(c, {1: np.uint8, 2: np.uint16, 4: np.int32}[len(c) // rows]), own) for own, c in zip(sizes, cells)]
                    yield answers(range(len(told.value[0])), [inspected(codes, x, bits) for x, bits in zip(*told.value)])

        got = parts.select("rows", "sizes", *[f"c{i}" for i in held]).mapInArrow(run, ANSWERS).collect()  # a row for each set and part
        out = dict(asked)
        for r in got:
            out[masks[r["at"]]] &= r["held"]
        return out, gathered(got)


def counts_broadcast(df: DataFrame, attrs: list[str], masks: list[int], k: int) -> dict[int, int]:
    """Codes broadcast whole where they fit, else dealt in parts."""
    try:
        return BroadcastCodes(df, attrs, k).counts(masks)
    except MemoryError:
        return (DealtCodes(df, attrs, k).counts if dealable(df, attrs) else lambda masks: counts_by_grouping_sets(df, attrs, masks))(masks)


def encode(table: pa.Table) -> list[tuple[np.ndarray, int]]:
    """(codes, number of codes) of each column, in the order of the values: nulls first, NaN last, -0.0 as 0.0."""
    out = []
    for column in table.columns:
        c = column.combine_chunks()
        if pa.types.is_nested(c.type):
            c = pa.array([None if v is None else repr(v) for v in c.to_pylist()], pa.string())
        if pa.types.is_null(c.type):
            c = c.cast(pa.string())
        null = np.asarray(c.is_null())
        if pa.types.is_floating(c.type):
            values = np.asarray(c.fill_null(0)) + 0.0  # -0.0 becomes 0.0; all NaN are one value, after the others
            values, codes = np.unique(values, return_inverse=True, equal_nan=True)
        elif pa.types.is_integer(c.type) or pa.types.is_temporal(c.type):
            values, codes = np.unique(np.asarray(c.fill_null(pa.scalar(0).cast(c.type) if pa.types.is_integer(c.type) else pa.scalar(0, pa.int64()).cast(c.type) if c.type.bit_width == 64 else pa.scalar(0, pa.int32()).cast(c.type))), return_inverse=True)
        else:
            coded = c.dictionary_encode()
            words = coded.dictionary
            rank = np.empty(len(words), np.int64)
            rank[np.asarray(pa.compute.sort_indices(words))] = np.arange(len(words))
            codes, values = rank[np.asarray(coded.indices.fill_null(0))] if len(words) else np.zeros(len(c), np.int64), words
        codes = np.where(null, 0, codes + 1).astype(np.int32) if null.any() else codes.astype(np.int32)
        out.append((codes, max(1, len(values) + int(null.any()))))
    return out


def class_numbers(codes: list[tuple[np.ndarray, int]], mask: int) -> tuple[np.ndarray, int]:
    """(a number for each row, bound of the numbers): equal for rows equal on the set, in the order of its attributes by size."""
    n = len(codes[0][0])
    key, size = np.zeros(n, np.int64), 1
    for i in sorted(members(mask), key=lambda i: codes[i][1]):
        c, own = codes[i]
        if size * own >= 1 << 62:
            key, size = np.unique(key, return_inverse=True)[1].astype(np.int64), n
        key, size = key * own + c, size * own
    return key, size


def count_distinct(codes: list[tuple[np.ndarray, int]], mask: int) -> int:
    if not len(codes[0][0]):
        return 0
    key, size = class_numbers(codes, mask)
    if size <= 4 * len(key):
        seen = np.zeros(size, bool)
        seen[key] = True
        return int(seen.sum())
    key.sort()
    return int((key[1:] != key[:-1]).sum()) + 1


#: Agreements that an inspection returns, and pairs of rows that it looks at for them.
AGREED, LOOKED = 64, 4096
ANSWERS = "at int, held long, agreed binary"


def answers(at, found: list[tuple[int, np.ndarray]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), pa.array([held for held, _ in found], pa.int64()), pa.array([x.tobytes() for _, x in found], pa.binary())], ["at", "held", "agreed"])


def gathered(got: list) -> np.ndarray:
    return np.unique(np.frombuffer(b"".join(r["agreed"] for r in got), np.int64))


def inspected(codes: list[tuple[np.ndarray, int]], mask: int, asked: int) -> tuple[int, np.ndarray]:
    """Which of the asked bits hold: bit a, that the set determines attribute a; bit m, that no two rows are equal on the set.

    Also agreements: all attributes that two rows of one class share, for some such pairs, those that share most first."""
    m, n = len(codes), len(codes[0][0])
    key, _ = class_numbers(codes, mask) if n else (np.empty(0, np.int64), 1)
    alone = np.sort(key)
    if not (alone[1:] == alone[:-1]).any():
        return asked, np.empty(0, np.int64)
    order = np.argsort(key)
    same = np.flatnonzero(key[order[1:]] == key[order[:-1]])
    left, right = order[same], order[same + 1]
    held, refuting = 0, []
    for a in members(asked & (1 << m) - 1):
        c = codes[a][0]
        unlike = np.flatnonzero(c[left[:LOOKED]] != c[right[:LOOKED]])
        if not len(unlike):
            unlike = np.flatnonzero(c[left] != c[right])
        if len(unlike):
            refuting.append(unlike[:: -(-len(unlike) // (LOOKED // 8))])
        else:
            held |= 1 << a
    looked = np.unique(np.concatenate([*refuting, np.arange(0, len(left), -(-len(left) // LOOKED))]))
    looked = looked[:: -(-len(looked) // (4 * LOOKED))]
    left, right = left[looked], right[looked]
    agreed = np.zeros(len(left), np.int64)
    for a, (c, _) in enumerate(codes):
        agreed |= (c[left] == c[right]).astype(np.int64) << a
    agreed = np.unique(agreed)
    return held, agreed[np.argsort(-np.bitwise_count(agreed), kind="stable")[:AGREED]]


def swapped(codes: list[tuple[np.ndarray, int]], question: tuple[int, int, int, bool]) -> bool:
    """question (context, a, b, descending): whether two rows of one class of the context are ordered one way by a and the other way by b."""
    context, i, j, descending = question
    (a, size_a), (b, size_b) = codes[i], codes[j]
    if not len(a):
        return False
    group, size = class_numbers(codes, context)
    if size * size_a >= 1 << 62:
        group = np.unique(group, return_inverse=True)[1].astype(np.int64)
    key = group * size_a + a
    order = np.argsort(key, kind="stable")
    key, own, group = key[order], b[order].astype(np.int64), group[order]
    if descending:
        own = size_b - 1 - own
    first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    low, high, group = np.minimum.reduceat(own, first), np.maximum.reduceat(own, first), group[first]
    lead = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]]))
    turn = np.zeros(len(group), np.int64)
    turn[lead] = 1
    base = (np.cumsum(turn) - 1) * size_b  # each class above all before it
    reach = np.maximum.accumulate(base + high)
    return bool((reach[:-1] > (base + low)[1:]).any())
