"""Evidence of row pairs for keys and functional dependencies: which attributes differ, as native bit expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from depmine.functions.bits import from_words

WORD = 62
#: Distinct evidence that the driver is to hold.
MOST = 5_000_000


def differs(attrs: list[str], left: str = "l_", right: str = "r_") -> list[Column]:
    """Columns ev0, ev1, ...: bit i of the whole is set where attribute i differs; null equals null."""
    out = []
    for w in range(0, max(1, len(attrs)), WORD):
        total = F.lit(0).cast("long")
        for i, a in enumerate(attrs[w : w + WORD]):
            total = total + F.when(F.col(left + a).eqNullSafe(F.col(right + a)), F.lit(0)).otherwise(F.lit(1 << i)).cast("long")
        out.append(total.alias(f"ev{w // WORD}"))
    return out


def histogram(pairs: DataFrame, columns) -> DataFrame:
    """Distinct evidence with its number of pairs; map-side combine keeps the exchange tiny."""
    shown = pairs.select(*columns)
    return shown.groupBy(*shown.columns).agg(F.count("*").alias("n_pairs"))


def masks(evidence: DataFrame, most: int = MOST) -> dict[int, int]:
    """The distinct masks on the driver, where covers are searched; refuses more than `most` of them."""
    words = sorted((c for c in evidence.columns if c != "n_pairs"), key=lambda c: int(c.lstrip("abcdefghijklmnopqrstuvwxyz")))
    rows = evidence.limit(most + 1).collect()
    if len(rows) > most:
        raise MemoryError(f"more than {most} distinct evidence sets")
    return {from_words([r[w] for w in words]): r["n_pairs"] for r in rows}
