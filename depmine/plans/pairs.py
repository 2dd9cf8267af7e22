"""Search from row pairs: evidence of pairs, then covers. Pairs are quadratic, so every plan refuses beyond `max_pairs`."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from depmine.operators import compare, cover, distribute, evidence
from depmine.sources.io import materialize

from .result import Meter


def compacted(df: DataFrame, attrs: list[str], multiplicity: bool = False) -> tuple[DataFrame, bool, int]:
    """Distinct rows with two hashes that tell them apart (and _m, how often each occurs), whether rows repeat, and their number."""
    nulls = [F.isnull(a) for a in attrs]
    rows = df.groupBy(*attrs).agg(F.count("*").alias("_m"))
    rows = materialize(rows.withColumns({"_h1": F.xxhash64(F.lit(1), *attrs, *nulls), "_h2": F.xxhash64(F.lit(2), *attrs, *nulls)}), "rows")  # each round reads it again
    stat = rows.agg(F.count("*").alias("n"), F.max("_m").alias("m")).first()
    return rows if multiplicity else rows.drop("_m"), (stat["m"] or 0) > 1, stat["n"]


ORDER = ["_h1", "_h2"]


def pairs_of(rows: DataFrame, attrs: list[str], plan: str, memory: str, k: int, dedupe: bool = False) -> DataFrame:
    if plan == "rescan":
        return distribute.triangle(rows, k, ORDER) if memory == "resident" else distribute.cartesian(rows, ORDER)
    if memory == "resident":
        return distribute.blocks(rows, attrs, k, ORDER, dedupe)
    parts = None  # one keyed join for each attribute: classes are spread and split by the engine
    for a in attrs:
        left, right = distribute.sided(rows, "l_"), distribute.sided(rows, "r_")
        same = F.col(f"l_{a}").eqNullSafe(F.col(f"r_{a}")) & (F.struct(F.col("l__h1"), F.col("l__h2")) < F.struct(F.col("r__h1"), F.col("r__h2")))
        own = left.hint("merge").join(right, same)
        parts = own if parts is None else parts.unionByName(own)
    return parts


def evidence_of(rows: DataFrame, n: int, attrs: list[str], plan: str, memory: str, k: int, dedupe: bool = False, form: compare.Form | None = None, distinct: bool = False) -> DataFrame:
    """The histogram of all pairs that the plan forms, compared in tasks by blocks; types that tasks cannot code, and pairs counted at one shared attribute only, are formed as rows. distinct: the resident rescan plan need not count the pairs."""
    form = form or compare.Form(attrs)
    if dedupe or not form.fits(rows):
        return evidence.histogram(pairs_of(rows, attrs, plan, memory, k, dedupe), evidence.differs(attrs))
    if plan == "rescan":
        return compare.triangle(rows, n, k, ORDER, form, distinct) if memory == "resident" else compare.cartesian(rows, n, ORDER, form)
    return compare.blocks(rows, k, ORDER, form, apart=memory == "spill")


def within_classes(rows: DataFrame, attrs: list[str]) -> int:
    """The comparisons of the reuse plan, a pair once for each value it shares."""
    return rows.transform(distribute.block_stats, attrs).agg(F.sum("work").alias("w")).first()["w"] or 0


def guard(pairs: int, max_pairs: int | None) -> int:
    if max_pairs is not None and pairs > max_pairs:
        raise MemoryError(f"{pairs} pairs exceed the limit of {max_pairs}; use method='hybrid'")
    return pairs


def run(df: DataFrame, attrs: list[str], kind: str, plan: str, memory: str, k: int, max_lhs: int | None, meter: Meter, max_pairs: int = 5_000_000_000, dedupe: bool = False, covers_in: str = "driver", max_covers: int | None = None) -> list[tuple[int, int]]:
    """max_pairs, max_covers: refuse beyond so many pairs of rows, or dependencies for the driver."""
    with meter.phase("data"):
        rows, repeated, n = compacted(df, attrs)
        total = guard(n * (n - 1) // 2 if plan == "rescan" else within_classes(rows, attrs), max_pairs)
        seen = evidence.masks(evidence_of(rows, n, attrs, plan, memory, k, dedupe))
        compared = sum(seen.values())
        everything = (1 << len(attrs)) - 1
        if plan == "reuse" and n > 1:
            seen.setdefault(everything, 0)  # pairs that share no value are not formed; their mask says only that no column is constant
    meter.step("data", 1, len(seen), 0, compared if plan == "reuse" else total)
    with meter.phase("covers"):
        if kind == "ucc":
            found = [] if repeated else [(x, 0) for x in cover.minimal(seen, max_lhs, most=max_covers)]
        else:
            found = cover.per_rhs(df.sparkSession, seen, len(attrs), max_lhs, covers_in, max_covers)
            if plan == "reuse" and n > 1:
                found = _without_false_constants(rows, attrs, found, seen)
    return found


def _without_false_constants(rows, attrs, found, seen):
    """The mask of all attributes was assumed for pairs that share nothing. Where all pairs share a value it may be absent: right sides that it alone refutes are checked."""
    everything = (1 << len(attrs)) - 1
    if seen[everything] or len(seen) == 1:
        return found
    # the assumed mask matters only for X = {} -> A: every other refutation needs an agreeing attribute
    known = [e for e in seen if e != everything]
    out = []
    constant = {a for a in range(len(attrs)) if not any(e >> a & 1 for e in known)}
    distinct = rows.agg(*[F.count_distinct(F.struct(F.col(a))).alias(a) for a in attrs]).first() if constant else {}
    for a in constant:
        if distinct[attrs[a]] <= 1:
            out.append((0, 1 << a))
    settled = {1 << a for a in constant if distinct[attrs[a]] <= 1}
    return [x for x in found if x[1] not in settled] + out
