"""Preparation of relations: projection, filters, derived columns, encoding of types that cannot be grouped."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


def project(df: DataFrame, include=None, exclude=(), rename=None) -> DataFrame:
    chosen = [c for c in (include or df.columns) if c not in set(exclude)]
    return df.select(*[F.col(c).alias((rename or {}).get(c, c)) for c in chosen])


def flatten(df: DataFrame, separator: str = "_") -> DataFrame:
    """Structs by leaf, maps as sorted arrays of entries; the rest unchanged."""
    out = []
    for field in df.schema.fields:
        if isinstance(field.dataType, T.StructType):
            out += [F.col(f"`{field.name}`.`{f.name}`").alias(f"{field.name}{separator}{f.name}") for f in field.dataType.fields]
        elif isinstance(field.dataType, T.MapType):
            out.append(F.array_sort(F.map_entries(f"`{field.name}`")).alias(field.name))
        else:
            out.append(F.col(f"`{field.name}`"))
    flat = df.select(*out)
    return flatten(flat, separator) if any(isinstance(f.dataType, (T.StructType, T.MapType)) for f in flat.schema.fields) else flat


def array_to_columns(df: DataFrame, column: str, size: int, prefix: str | None = None) -> DataFrame:
    keep = [F.col(c) for c in df.columns if c != column]
    return df.select(*keep, *[F.get(F.col(column), F.lit(i)).alias(f"{prefix or column}{i}") for i in range(size)])


def hash_slice(df: DataFrame, column: str, modulus: int, keep: int = 0) -> DataFrame:
    """A deterministic slice of the rows, the same on every run and partitioning."""
    return df.where(F.pmod(F.xxhash64(column), F.lit(modulus)) == keep)


def derive(df: DataFrame, expressions: dict[str, str]) -> DataFrame:
    """Further columns by SQL expression: string, date, math, JSON, array and map functions."""
    return df.withColumns({name: F.expr(e) for name, e in expressions.items()})


def compact(df: DataFrame) -> DataFrame:
    """Distinct rows with their multiplicity; equal rows never refute a functional dependency."""
    return df.groupBy(*df.columns).agg(F.count("*").alias("multiplicity"))


def distinct_nulls(df: DataFrame, attrs: list[str]) -> DataFrame:
    """null_mode `distinct`: each null becomes a value of its own, by row."""
    tag = F.monotonically_increasing_id()
    return df.select(*[F.when(F.col(a).isNotNull(), F.concat(F.lit("v"), F.col(a).cast("string"))).otherwise(F.concat(F.lit("n"), tag.cast("string"))).alias(a) for a in attrs])


def short_keys(df: DataFrame, attrs: list[str], over: int = 64) -> DataFrame:
    """Texts longer than `over` replaced by a 256-bit digest before any exchange; classes stay the same."""
    return df.select(*[F.when(F.length(a) > over, F.sha2(F.col(a), 256)).otherwise(F.col(a)).alias(a) if isinstance(df.schema[a].dataType, T.StringType) else F.col(a) for a in attrs])


def profile_schema(df: DataFrame, exclude=(), max_distinct_ratio: float = 1.0) -> list[str]:
    """Groupable columns, without those whose estimated distinct share exceeds the ratio; one pass."""
    attrs = [f.name for f in df.schema.fields if f.name not in set(exclude) and not isinstance(f.dataType, T.MapType)]
    if max_distinct_ratio >= 1:
        return attrs
    seen = df.agg(F.count("*").alias("_n"), *[F.approx_count_distinct(a).alias(a) for a in attrs]).first()
    return [a for a in attrs if seen[a] <= max_distinct_ratio * max(1, seen["_n"])]


def cells(df: DataFrame, attrs: list[str]) -> tuple[Column, list[str]]:
    """The values of a row as an array of (attr, v0, v1, ...) with one v for each type among the attributes, and the names of these fields.

    Of the v of one element only that of its attribute's type is set, so that
    grouping by them compares every value by its own type.
    """
    kind = {a: T.StringType() if isinstance(df.schema[a].dataType, T.NullType) else df.schema[a].dataType for a in attrs}
    kinds = list({k.simpleString(): k for k in kind.values()}.values())
    slots = [f"v{i}" for i in range(len(kinds))]
    each = [F.struct(F.lit(n).alias("attr"), *[(F.col(a) if kind[a].simpleString() == k.simpleString() else F.lit(None)).cast(k).alias(s) for s, k in zip(slots, kinds)]) for n, a in enumerate(attrs)]
    return F.array(*each), slots
