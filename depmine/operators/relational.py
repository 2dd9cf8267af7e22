"""Joins that are not one keyword in Spark: as-of and band joins, and the frames of order checks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def as_of(left: DataFrame, right: DataFrame, on: str, by: list[str], values: list[str]) -> DataFrame:
    """Each left row with the values of the latest right row at or before it, within `by`: one union and one window instead of a range join."""
    l = left.select(*[F.col(c) for c in left.columns], *[F.lit(None).cast(right.schema[v].dataType).alias(f"_{v}") for v in values], F.lit(1).alias("_side"))  # noqa: E741
    r = right.select(*[F.col(c) if c in (on, *by) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns], *[F.col(v).alias(f"_{v}") for v in values], F.lit(0).alias("_side"))
    w = Window.partitionBy(*by).orderBy(on, "_side").rowsBetween(Window.unboundedPreceding, 0)
    filled = l.unionByName(r).withColumns({f"_{v}": F.last(f"_{v}", ignorenulls=True).over(w) for v in values})
    return filled.where("_side = 1").select(*left.columns, *[F.col(f"_{v}").alias(f"as_of_{v}") for v in values])


def band(left: DataFrame, right: DataFrame, x: str, y: str, width: float) -> DataFrame:
    """Pairs with |x - y| <= width by an equi-join on buckets: each right row goes to its bucket and the two beside it."""
    a = left.withColumn("_b", F.floor(F.col(x) / width))
    b = right.withColumn("_b", F.explode(F.transform(F.array(F.lit(-1), F.lit(0), F.lit(1)), lambda d: F.floor(F.col(y) / width) + d)))
    return a.join(b, "_b").where(F.abs(F.col(x) - F.col(y)) <= width).drop("_b")
