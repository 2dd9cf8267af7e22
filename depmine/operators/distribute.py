"""How rows and pairs reach workers: triangle, blocks, cartesian, bands, columns, candidates, random groups, windows.

`k` is the logical number of workers. Routing is a column, so that data received
and work done can be counted exactly, whatever machine runs the job.
"""

from __future__ import annotations

import random
from functools import reduce
from math import isqrt

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from depmine.functions.prep import cells
from depmine.sources.io import materialize

#: A class beyond this many rows is not given to one worker.
LARGEST_CLASS = 2_000_000


def triangle_side(k: int) -> int:
    """The largest l with l(l+1)/2 cells for k workers."""
    side = 1
    while (side + 1) * (side + 2) // 2 <= k:
        side += 1
    return side


def sided(df: DataFrame, prefix: str, keep=()) -> DataFrame:
    return df.select(*[F.col(c).alias(f"{prefix}{c}") if c not in keep else F.col(c) for c in df.columns])


def route(df: DataFrame, side: int, anchor: Column, base: Column | None = None) -> DataFrame:
    """Each row to the `side` cells (x <= y) that touch its anchor; column cell, and whether it stands left (anchor is x) or right (anchor is y)."""
    other = F.explode(F.sequence(F.lit(0), F.lit(side - 1))) if isinstance(side, int) else F.explode(F.sequence(F.lit(0), side - 1))
    out = df.withColumn("_a", anchor.cast("int")).withColumn("_o", other)
    x, y = F.least("_a", "_o"), F.greatest("_a", "_o")
    cell = x * F.lit(side) + y if isinstance(side, int) else x * side + y
    return out.withColumn("cell", cell if base is None else base + cell)


def _later(order: list[str]) -> Column:
    """Left before right: by anchor, within one anchor by the columns that tell rows apart."""
    return (F.col("l__a") < F.col("r__a")) | (F.struct(*[f"l_{c}" for c in order]) < F.struct(*[f"r_{c}" for c in order]))


def triangle_routes(df: DataFrame, k: int, order: list[str], anchor: Column | None = None) -> DataFrame:
    side = triangle_side(k)
    return route(df, side, anchor if anchor is not None else F.pmod(F.xxhash64(*order), F.lit(side)))


def triangle(df: DataFrame, k: int, order: list[str], anchor: Column | None = None, on: list[str] = []) -> DataFrame:  # noqa: B006
    """Every unordered pair of rows exactly once: columns l_*, r_*, cell. order: columns that tell rows apart; on: columns in which the two must agree."""
    routed = triangle_routes(df, k, order, anchor)
    left = sided(routed.where("_a <= _o"), "l_", ("cell",))
    right = sided(routed.where("_a >= _o"), "r_", ("cell",))
    met = left.join(right.withColumnRenamed("cell", "_cell"), reduce(lambda a, b: a & b, [F.col(f"l_{c}").eqNullSafe(F.col(f"r_{c}")) for c in on], F.col("cell") == F.col("_cell")))
    return met.drop("_cell").where(_later(order))


def cartesian(df: DataFrame, order: list[str], on: list[str] = []) -> DataFrame:  # noqa: B006
    """All ordered pairs, mirrors filtered. Quadratic by design: the scarce-memory plan of the pair methods, behind their limit on pairs."""
    left, right = sided(df, "l_"), sided(df, "r_")
    before = F.struct(*[f"l_{c}" for c in order]) < F.struct(*[f"r_{c}" for c in order])
    return left.join(right, reduce(lambda a, b: a & b, [F.col(f"l_{c}").eqNullSafe(F.col(f"r_{c}")) for c in on], before))


def _by_value(df: DataFrame, attrs: list[str]) -> tuple[DataFrame, list[str]]:
    """A row for each attribute of each row: attr and the typed value, and the names of the columns that name a class."""
    values, slots = cells(df, attrs)
    flat = df.withColumn("_c", F.explode(values)).select(*df.columns, F.col("_c.attr").alias("attr"), *[F.col(f"_c.{s}").alias(f"_{s}") for s in slots])
    return flat, ["attr", *[f"_{s}" for s in slots]]


def block_stats(df: DataFrame, attrs: list[str]) -> DataFrame:
    """(attr, the value by type, size, work) of each class of each attribute with two rows or more."""
    flat, key = _by_value(df.select(*attrs), attrs)
    sizes = flat.groupBy(*key).agg(F.count("*").alias("size"))
    return sizes.where("size > 1").withColumn("work", F.expr("size * (size - 1) div 2"))


def block_routes(df: DataFrame, attrs: list[str], k: int, order: list[str]) -> DataFrame:
    """Each row to the cells of its classes: columns attr, block, cell, worker.

    A class gets reducers in proportion to its share of the work: a large one a
    triangle of its own, small ones are packed by hash. Large classes are told
    to all tasks (each has three of k reducers or more, so they are at most a
    third of k), the others are looked up by exchange.
    """
    flat, key = _by_value(df, attrs)
    short = [f"_k{i}" for i in range(len(key))]
    stats = flat.groupBy(*[F.col(c).alias(s) for c, s in zip(key, short)]).agg(F.count("*").alias("_size"), F.min(F.struct(*order)).alias("block")).where("_size > 1").withColumn("_work", F.expr("_size * (_size - 1) div 2"))
    stats = materialize(stats, "blocks")
    whole = stats.agg(F.sum("_work").alias("w")).first()["w"] or 1
    reducers = F.greatest(F.lit(1), F.floor(F.lit(float(k)) * F.col("_work") / F.lit(float(whole))))
    sized = stats.select(*short, "block", F.greatest(F.lit(1), F.floor((F.sqrt(F.lit(8) * reducers + 1) - 1) / 2)).cast("int").alias("_side"))
    met = reduce(lambda a, b: a & b, [F.col(c).eqNullSafe(F.col(s)) for c, s in zip(key, short)])
    marked = flat.join(F.broadcast(sized.where("_side > 1")), met, "left").select(*flat.columns, "block", "_side")
    rest = marked.where("_side is null").drop("block", "_side").join(sized.where("_side = 1"), met).select(*flat.columns, "block", "_side")
    rows = rest.unionByName(marked.where("_side is not null")).select(*df.columns, "attr", "block", "_side")
    routed = route(rows, F.col("_side"), F.pmod(F.xxhash64(*order), F.col("_side")))
    return routed.withColumn("worker", F.pmod(F.xxhash64("attr", "block", "cell"), F.lit(k)).cast("int"))


def blocks(df: DataFrame, attrs: list[str], k: int, order: list[str], dedupe: bool = False) -> DataFrame:
    """Pairs that share a value, found within the classes; a pair comes once for each shared value, or with dedupe at its first shared attribute only."""
    key = ("attr", "block", "cell", "worker")
    routed = block_routes(df, attrs, k, order)
    left, right = sided(routed.where("_a <= _o"), "l_", key), sided(routed.where("_a >= _o"), "r_", key)
    pairs = left.join(right, list(key)).where(_later(order))
    if dedupe:
        first = F.lit(len(attrs))
        for i in range(len(attrs) - 1, -1, -1):
            first = F.when(F.col(f"l_{attrs[i]}").eqNullSafe(F.col(f"r_{attrs[i]}")), F.lit(i)).otherwise(first)
        pairs = pairs.where(F.col("attr") == first)
    return pairs


def positions(df: DataFrame, within: list[str], order: list[str], name: str = "_pos") -> DataFrame:
    """df with the place (from 0) of each row among those equal on `within`, by `order`; no class or table meets in one task.

    Rows are range partitioned; a class goes on in the next partitions only at
    their borders, so the table of what lies before a partition has at most one
    row for each of them.
    """
    parts = materialize(df.repartitionByRange(*within, *order).withColumn("_part", F.spark_partition_id()), "positions")
    local = F.row_number().over(Window.partitionBy("_part", *within).orderBy(*order))
    short = [f"_w{i}" for i in range(len(within))]
    sizes = parts.groupBy(F.col("_part").alias("_p"), *[F.col(c).alias(s) for c, s in zip(within, short)]).agg(F.count("*").alias("_n"))
    before = F.sum("_n").over(Window.partitionBy(*short).orderBy("_p").rowsBetween(Window.unboundedPreceding, -1))
    ahead = sizes.withColumn("_before", before).where("_before > 0").drop("_n")
    met = reduce(lambda a, b: a & b, [F.col(c).eqNullSafe(F.col(s)) for c, s in zip(within, short)], F.col("_part") == F.col("_p"))
    placed = parts.withColumn("_local", local).join(F.broadcast(ahead), met, "left")
    return placed.select(*df.columns, (F.col("_local") - 1 + F.coalesce("_before", F.lit(0))).alias(name))


def band_deal(stats: DataFrame, k: int, size: str = "size", tie: list[str] | None = None) -> DataFrame:
    """Classes by rising size in bands of k, one of each band to each worker: columns rank, worker."""
    keys = [size, *(tie or [c for c in stats.columns if c != size])]
    return positions(stats, [], keys, "rank").withColumn("worker", F.pmod(F.col("rank"), F.lit(k)).cast("int"))


def columns_deal(attrs: list[str], k: int) -> dict[str, int]:
    """Column j to worker j mod k."""
    return {a: i % k for i, a in enumerate(attrs)}


def dealt_columns(df: DataFrame, attrs: list[str], k: int) -> DataFrame:
    """(attr, worker, n_values): the columns of df dealt out as cells, and how many values of each its worker receives."""
    flat, (_, *slots) = _by_value(df.select(*attrs), attrs)
    deal = columns_deal(attrs, k)
    named = lambda of: F.get(F.array(*[F.lit(x) for x in of]), F.col("attr"))
    held = F.when(reduce(lambda a, b: a | b, [F.col(s).isNotNull() for s in slots]), F.lit(1))
    counted = flat.groupBy("attr").agg(F.count(held).alias("n_values"))
    return counted.select(named(attrs).alias("attr"), named([deal[a] for a in attrs]).alias("worker"), "n_values")


def candidates_deal(candidates: list, k: int) -> list[list]:
    """Candidates of a level round robin over k workers."""
    return [candidates[i::k] for i in range(k)]


class PairSchedule:
    """All pairs of groups, self-pairs included, in a seeded random order without replacement, k a round.

    The order is a keyed permutation of the pairs' numbers and a pair is made
    from its number on demand, so that no list of pairs exists, however many groups there are.
    """

    def __init__(self, groups: int, k: int, seed: int = 42):
        self.groups, self.k, self.total = groups, k, groups * (groups + 1) // 2
        self.rounds = -(-self.total // k)
        self.half = max(1, -(-(self.total - 1).bit_length() // 2))
        draw = random.Random(seed)
        self.keys = [draw.getrandbits(64) | 1 for _ in range(6)]

    def _scrambled(self, number: int) -> int:
        low_bits = (1 << self.half) - 1
        left, right = number >> self.half, number & low_bits
        for key in self.keys:
            left, right = right, left ^ ((right * 0x9E3779B97F4A7C15 + key) * key >> 37) & low_bits
        return left << self.half | right

    def pair(self, place: int) -> tuple[int, int]:
        number = self._scrambled(place)
        while number >= self.total:  # numbers beyond the pairs are walked over
            number = self._scrambled(number)
        b = (isqrt(8 * number + 1) - 1) // 2
        return number - b * (b + 1) // 2, b

    def round(self, number: int) -> list[tuple[int, int]]:
        return [self.pair(i) for i in range(number * self.k, min(self.total, (number + 1) * self.k))]


def group_schedule(groups: int, k: int, seed: int = 42) -> list[tuple[int, int, int]]:
    """(g1, g2, round) of a whole schedule, for few groups."""
    schedule = PairSchedule(groups, k, seed)
    return [(a, b, r) for r in range(schedule.rounds) for a, b in schedule.round(r)]


def with_groups(df: DataFrame, groups: int, order: list[str], seed: int = 42) -> DataFrame:
    """A seeded random group for each row, stable over re-evaluation."""
    return df.withColumn("gid", F.pmod(F.xxhash64(F.lit(seed), *order), F.lit(groups)).cast("int"))


def group_routes(df: DataFrame, pairs: list[tuple[int, int]]) -> tuple[DataFrame, DataFrame]:
    """The left and the right rows of the given pairs of groups, with their cell. df has gid; a round's pairs are k rows and broadcast."""
    table = F.broadcast(df.sparkSession.createDataFrame([(a, b, i) for i, (a, b) in enumerate(pairs)], "g1 int, g2 int, cell int"))
    return df.join(table.select(F.col("g1").alias("gid"), "cell"), "gid"), df.join(table.select(F.col("g2").alias("gid"), "cell"), "gid")


def group_pairs(df: DataFrame, pairs: list[tuple[int, int]], order: list[str]) -> DataFrame:
    """All row pairs of the given pairs of groups."""
    left, right = (sided(x, p, ("cell",)) for x, p in zip(group_routes(df, pairs), ("l_", "r_")))
    different = F.struct(*[f"l_{c}" for c in order]) < F.struct(*[f"r_{c}" for c in order])
    return left.join(right, "cell").where((F.col("l_gid") != F.col("r_gid")) | different)


def class_routes(df: DataFrame, attr: str, k: int, largest: int = LARGEST_CLASS) -> DataFrame:
    """Rows of the classes of attr with two rows or more, dealt whole to k workers in bands by size: column worker. Refuses a class beyond `largest` rows."""
    sizes = materialize(df.groupBy(F.col(attr).alias("_v")).agg(F.count("*").alias("size")).where("size > 1"), "class-sizes")
    most = sizes.agg(F.max("size").alias("m")).first()["m"] or 0
    if most > largest:
        raise MemoryError(f"a class of {most} rows for one worker, more than {largest}; use memory='spill'")
    deal = band_deal(sizes, k, tie=["_v"]).select("_v", "worker")
    return df.join(deal, F.col(attr).eqNullSafe(F.col("_v"))).drop("_v").repartition(k, "worker")


def led(routed: DataFrame, attr: str, distance: int, order: list[str], worker: str = "worker") -> DataFrame:
    """Pairs at exactly that distance within the classes that a worker holds: l_*, r_* and the worker."""
    row = F.struct(*[F.col(c) for c in routed.columns if c != worker])
    found = routed.select(worker, row.alias("l"), F.lead(row, distance).over(Window.partitionBy(worker, attr).orderBy(*order)).alias("r")).where("r is not null")
    return found.select(worker, *[F.col(f"{p}.{c}").alias(f"{p}_{c}") for p in "lr" for c in routed.columns if c != worker])


def meeting(placed: DataFrame, attr: str, distance: int) -> DataFrame:
    """The same pairs by a join of places (column _pos), which spreads one class over workers."""
    left, right = sided(placed.withColumn("_meet", F.col("_pos") + distance), "l_"), sided(placed, "r_")
    return left.join(right, F.col(f"l_{attr}").eqNullSafe(F.col(f"r_{attr}")) & (F.col("l__meet") == F.col("r__pos"))).drop("l__meet", "l__pos", "r__pos")


def window_pairs(df: DataFrame, attr: str, distance: int, order: list[str], mode: str = "lead", k: int = 8) -> DataFrame:
    """Pairs at exactly that distance within the classes of attr: classes dealt in bands (`lead`), or a keyed join of places (`join`)."""
    if mode == "lead":
        return led(class_routes(df, attr, k), attr, distance, order).drop("worker")
    return meeting(positions(df, [attr], order), attr, distance)


def load_of(pairs: DataFrame, received: DataFrame, cell: str, width: int) -> DataFrame:
    """(worker, x, y): values received and values compared by each cell."""
    x = received.groupBy(cell).agg((F.count("*") * width).alias("x"))
    y = pairs.groupBy(cell).agg((F.count("*") * width).alias("y"))
    return x.join(y, cell, "left").select(F.col(cell).alias("worker"), "x", F.coalesce("y", F.lit(0)).alias("y"))
