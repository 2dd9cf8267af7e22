"""Whether one partition refines another: by counts, by constancy within classes, by order within classes."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from depmine.sources.io import materialize


def by_counts(count_x: int, count_xa: int) -> bool:
    return count_x == count_xa


def level_tests(spark, level: dict[int, int], before: dict[int, int], k: int = 8) -> DataFrame:
    """(lhs, rhs, holds) of every candidate of a level: its counts dealt to k workers, the counts of the level before broadcast to each.

    For levels that are large for the driver; masks travel as text.
    """
    few = F.broadcast(spark.createDataFrame([(str(m), n) for m, n in before.items()], "lhs string, before long"))  # one row for each set of a level
    tests = [(str(x ^ 1 << a), 1 << a, n) for x, n in level.items() for a in range(x.bit_length()) if x >> a & 1]
    dealt = spark.createDataFrame([(lhs, str(rhs), n) for lhs, rhs, n in tests], "lhs string, rhs string, n long").repartition(k)
    return dealt.join(few, "lhs").select("lhs", "rhs", (F.col("n") == F.col("before")).alias("holds"))


def by_minmax(df: DataFrame, lhs: list[str], rhs: list[str]) -> DataFrame:
    """One exchange answers every lhs -> a of one left side: (rhs, holds)."""
    same = df.groupBy(*lhs).agg(*[(F.min(rank_key(a)).eqNullSafe(F.max(rank_key(a)))).alias(f"_{i}") for i, a in enumerate(rhs)])
    row = same.agg(*[F.coalesce(F.bool_and(f"_{i}"), F.lit(True)).alias(f"_{i}") for i in range(len(rhs))])
    return row.select(F.explode(F.array(*[F.struct(F.lit(a).alias("rhs"), F.col(f"_{i}").alias("holds")) for i, a in enumerate(rhs)])).alias("r")).select("r.*")


def witness(df: DataFrame, lhs: list[str], rhs: str) -> DataFrame:
    """Classes of lhs with more than one value of rhs."""
    return df.groupBy(*lhs).agg(F.min(rank_key(rhs)).alias("_a"), F.max(rank_key(rhs)).alias("_b")).where("not (_a <=> _b)").select(*lhs, F.col("_a.v").alias("value_1"), F.col("_b.v").alias("value_2"))


def rank_key(a: str):
    """Orders nulls first, which min and max would skip."""
    return F.struct(F.col(a).isNotNull().alias("n"), F.col(a).alias("v"))


def order_runs(df: DataFrame, context: list[str], a: str, others: list[str]) -> DataFrame:
    """(context, a, lo0, hi0, lo1, ...): the extremes of every other attribute for each value of a within each class. Equal values of a are one run, so ties never count."""
    return df.groupBy(*context, a).agg(*[f(rank_key(b)).alias(f"{n}{i}") for i, b in enumerate(others) for n, f in (("lo", F.min), ("hi", F.max))])


def swap_flags(df: DataFrame, context: list[str], a: str, others: list[str], spread: bool = False) -> DataFrame:
    """The runs with, for each other attribute, whether it runs back behind an earlier run: up0, down0, up1, ...

    One pass checks all attributes and both directions of one (context, a). With
    spread, no class meets in one task: runs are range partitioned by class and a,
    and what came before a partition, one row for each partition at most, is
    told to all tasks.
    """
    runs = order_runs(df, context, a, others)
    ends = [(f"hi{i}", F.max) for i in range(len(others))] + [(f"lo{i}", F.min) for i in range(len(others))]
    if spread:
        runs = materialize(runs.withColumn("_key", rank_key(a)).repartitionByRange(*context, "_key").withColumn("_part", F.spark_partition_id()), "ranges")
        short = [f"_c{i}" for i in range(len(context))]
        most = runs.groupBy(F.col("_part").alias("_p"), *[F.col(c).alias(s) for c, s in zip(context, short)]).agg(*[f(c).alias(c) for c, f in ends])
        over = Window.partitionBy(*short).orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)
        ahead = most.select("_p", *short, *[f(c).over(over).alias(f"_{c}") for c, f in ends], F.count("*").over(over).alias("_n")).where("_n > 0").drop("_n")
        within = Window.partitionBy("_part", *context).orderBy("_key").rowsBetween(Window.unboundedPreceding, -1)
        met = reduce(lambda x, y: x & y, [F.col(c).eqNullSafe(F.col(s)) for c, s in zip(context, short)], F.col("_part") == F.col("_p"))
        local = runs.select("*", *[f(c).over(within).alias(f"_own_{c}") for c, f in ends]).join(F.broadcast(ahead), met, "left")
        reach = {c: (F.greatest if f is F.max else F.least)(f"_own_{c}", f"_{c}") for c, f in ends}
    else:
        within = Window.partitionBy(*context).orderBy(rank_key(a)).rowsBetween(Window.unboundedPreceding, -1)
        local = runs.select("*", *[f(c).over(within).alias(f"_own_{c}") for c, f in ends])
        reach = {c: F.col(f"_own_{c}") for c, _ in ends}
    up = [F.coalesce(reach[f"hi{i}"] > F.col(f"lo{i}"), F.lit(False)).alias(f"up{i}") for i in range(len(others))]
    down = [F.coalesce(reach[f"lo{i}"] < F.col(f"hi{i}"), F.lit(False)).alias(f"down{i}") for i in range(len(others))]
    return local.select(*context, a, *up, *down)


def swaps(df: DataFrame, context: list[str], a: str, b: str, descending: bool = False, spread: bool | None = None) -> DataFrame:
    """(context, a) where b runs back against the order of a within a class: empty if a and b are compatible. Without a context the runs are always spread."""
    return swap_flags(df, context, a, [b], not context if spread is None else spread).where("down0" if descending else "up0").select(*context, a)


def compatible(df: DataFrame, context: list[str], a: str, b: str, descending: bool = False) -> bool:
    return swaps(df, context, a, b, descending).isEmpty()
