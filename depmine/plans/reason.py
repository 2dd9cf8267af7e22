"""Uses of discovered dependencies: schema design, cleaning, query simplification, change over time."""

from __future__ import annotations

from functools import reduce
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from depmine.operators.refine import rank_key

FDs = list[tuple[frozenset, str]]


def as_sets(rows) -> FDs:
    return [(frozenset(r["lhs"].split(",")) - {""}, r["rhs"]) for r in rows]


def closure(attrs, fds: FDs) -> frozenset:
    out = set(attrs)
    while more := {a for x, a in fds if x <= out} - out:
        out |= more
    return frozenset(out)


def candidate_keys(attrs, fds: FDs, max_size: int | None = None) -> list[frozenset]:
    """Minimal sets whose closure is everything; attributes on no right side are in each of them."""
    attrs = frozenset(attrs)
    base = attrs - {a for _, a in fds}
    keys: list[frozenset] = []
    rest = sorted(attrs - base)
    for n in range(len(rest) + 1 if max_size is None else max_size + 1):
        for c in combinations(rest, n):
            x = base | set(c)
            if not any(k <= x for k in keys) and closure(x, fds) == attrs:
                keys.append(x)
    return keys


def minimal_cover(fds: FDs) -> FDs:
    out = list(dict.fromkeys(fds))
    for fd in list(out):
        rest = [f for f in out if f != fd]
        if fd[1] in closure(fd[0], rest):
            out = rest
    return out


def bcnf_violations(attrs, fds: FDs) -> FDs:
    return [(x, a) for x, a in fds if closure(x, fds) != frozenset(attrs)]


def shrink_group_by(columns, fds: FDs) -> list[str]:
    """Grouping columns that others determine are superfluous."""
    kept = list(columns)
    for c in reversed(list(columns)):
        if c in closure([k for k in kept if k != c], fds):
            kept.remove(c)
    return kept


def shrink_order_by(columns, ods) -> list[str]:
    """Sort columns behind one that orders them are superfluous. ods: (lhs, rhs) of ascending list dependencies."""
    kept: list[str] = []
    for c in columns:
        if not any((k, c) in set(ods) for k in kept):
            kept.append(c)
    return kept


def drop_distinct(columns, uccs) -> bool:
    return any(set(u.split(",")) <= set(columns) for u in uccs)


def violations(df: DataFrame, lhs: list[str], rhs: str) -> DataFrame:
    """Rows of classes of lhs with more than one value of rhs; only the broken classes go back into the join."""
    broken = df.groupBy(*lhs).agg((~F.min(rank_key(rhs)).eqNullSafe(F.max(rank_key(rhs)))).alias("_bad")).where("_bad").select(*[F.col(c).alias(f"_{c}") for c in lhs])
    same = reduce(lambda a, b: a & b, [F.col(c).eqNullSafe(F.col(f"_{c}")) for c in lhs])
    return df.join(broken, same, "left_semi")


def g3_error(df: DataFrame, lhs: list[str], rhs: str) -> DataFrame:
    """(n_rows, n_delete): how many rows must go for lhs -> rhs to hold."""
    sizes = df.groupBy(*lhs, rhs).agg(F.count("*").alias("n")).groupBy(*lhs).agg(F.sum("n").alias("n"), F.max("n").alias("most"))
    return sizes.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n_rows"), F.coalesce(F.sum(F.col("n") - F.col("most")), F.lit(0)).alias("n_delete"))


def duplicate_keys(df: DataFrame, ucc: list[str]) -> DataFrame:
    return df.groupBy(*ucc).agg(F.count("*").alias("n_rows")).where("n_rows > 1")


def dc_violations(df: DataFrame, predicates, key: str) -> DataFrame:
    """(t1, t2): pairs of keys that satisfy all predicates (attribute, operator); equalities become the join's key."""
    l, r = df.select(*[F.col(c).alias(f"l_{c}") for c in df.columns]), df.select(*[F.col(c).alias(f"r_{c}") for c in df.columns])
    ops = {"=": lambda x, y: x == y, "!=": lambda x, y: x != y, "<": lambda x, y: x < y, "<=": lambda x, y: x <= y, ">": lambda x, y: x > y, ">=": lambda x, y: x >= y}
    same = reduce(lambda a, b: a & b, [ops[o](F.col(f"l_{a}"), F.col(f"r_{a}")) for a, o in predicates])
    return l.join(r, same & (F.col(f"l_{key}") != F.col(f"r_{key}"))).select(F.col(f"l_{key}").alias("t1"), F.col(f"r_{key}").alias("t2"))


def compare(old: DataFrame, new: DataFrame) -> DataFrame:
    """(dependency columns, change): what a later discovery gained or lost."""
    keys = old.columns
    joined = old.withColumn("_o", F.lit(1)).join(new.withColumn("_n", F.lit(1)), keys, "full_outer")
    return joined.select(*keys, F.when(F.col("_o").isNull(), "gained").when(F.col("_n").isNull(), "lost").otherwise("kept").alias("change"))
