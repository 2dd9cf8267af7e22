"""Attribute sets as integer masks, on the driver and as columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def members(mask: int) -> list[int]:
    return [i for i in range(mask.bit_length()) if mask >> i & 1]


def names(mask: int, attrs: list[str]) -> str:
    """Comma-joined, name-sorted members: the same text in every engine."""
    return ",".join(sorted(attrs[i] for i in members(mask)))


def mask_of(columns, attrs: list[str]) -> int:
    return sum(1 << attrs.index(c) for c in columns)


def subset(inner: int, outer: int) -> bool:
    return inner & ~outer == 0


def antichain(masks) -> list[int]:
    """The masks that contain no other one, by size."""
    out: list[int] = []
    for m in sorted(set(masks), key=lambda x: (x.bit_count(), x)):
        if not any(subset(k, m) for k in out):
            out.append(m)
    return out


def popcount(column) -> Column:
    return F.bit_count(column)


def has_bit(column, bit: int) -> Column:
    return F.col(column).bitwiseAND(F.lit(1 << bit)) != 0 if isinstance(column, str) else column.bitwiseAND(F.lit(1 << bit)) != 0


def to_words(mask: int, words: int) -> list[int]:
    """A wide mask as 62-bit words."""
    return [mask >> 62 * i & (1 << 62) - 1 for i in range(words)]


def from_words(words) -> int:
    return sum(w << 62 * i for i, w in enumerate(words))
