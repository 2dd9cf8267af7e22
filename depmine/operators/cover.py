"""Minimal sets that meet every evidence set."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from depmine.functions.bits import antichain, members

#: The next set to branch on is the one with fewest open bits among so many uncovered ones, the smallest first.
LOOKED_AT = 32


class TooManyCovers(MemoryError):
    """More minimal sets than the driver is to hold."""


class Search:
    """Depth-first search over the transposed evidence: for each bit, the evidence sets that it meets.

    A bit tried is closed for its later siblings, and a choice that leaves an
    earlier one without a set of its own is cut off, so each minimal set comes once.
    rivals: bits that a chosen bit closes.
    """

    def __init__(self, sets, max_size: int | None = None, rivals: dict[int, int] | None = None, reduce: bool = True, most: int | None = None):
        self.sets = antichain(sets) if reduce else sorted(set(sets), key=lambda x: (x.bit_count(), x))
        self.max_size, self.rivals, self.most = max_size, rivals or {}, most
        found: dict[int, list[int]] = {}
        for n, s in enumerate(self.sets):
            for i in members(s):
                found.setdefault(i, []).append(n)
        self.hits = {i: sum(1 << n for n in own) for i, own in found.items()}
        self.every = (1 << len(self.sets)) - 1

    def covers(self, bits: int) -> bool:
        met = 0
        for i in members(bits):
            met |= self.hits.get(i, 0)
        return met == self.every

    def pivot(self, left: int, closed: int) -> int:
        best, least = 0, 1 << 30
        for _ in range(LOOKED_AT):
            low = left & -left
            open_bits = self.sets[low.bit_length() - 1] & ~closed
            if (n := open_bits.bit_count()) < least:
                best, least = open_bits, n
            left ^= low
            if not left or least <= 1:
                break
        return best

    def branches(self) -> list[tuple[int, int]]:
        """(first bit, bits closed before it): the search in parts."""
        out, closed = [], 0
        for i in members(self.pivot(self.every, 0)) if self.sets else []:
            out.append((i, closed))
            closed |= 1 << i
        return out

    def run(self, first: int | None = None, closed: int = 0) -> list[int]:
        if not self.sets:
            return [0]
        if self.sets[0] == 0:
            return []
        out: list[int] = []

        def go(chosen: int, size: int, left: int, alone: list[int], closed: int) -> None:
            if not left:
                out.append(chosen)
                if self.most is not None and len(out) > self.most:
                    raise TooManyCovers(f"more than {self.most} minimal sets")
                return
            if self.max_size is not None and size >= self.max_size:
                return
            for i in members(self.pivot(left, closed)):
                hit = self.hits[i]
                kept = [c & ~hit for c in alone]
                if all(kept):
                    go(chosen | 1 << i, size + 1, left & ~hit, [*kept, left & hit], closed | self.rivals.get(i, 0))
                closed |= 1 << i

        if first is None:
            go(0, 0, self.every, [], 0)
        elif self.max_size is None or self.max_size > 0:
            hit = self.hits[first]
            go(1 << first, 1, self.every & ~hit, [hit], closed | self.rivals.get(first, 0))
        return out


def minimal(sets, max_size: int | None = None, rivals: dict[int, int] | None = None, most: int | None = None) -> list[int]:
    """All minimal masks of at most max_size bits that share a bit with every set; none if a set is empty."""
    return Search(sets, max_size, rivals, most=most).run()


def minimal_in_tasks(spark: SparkSession, sets, max_size: int | None = None, rivals: dict[int, int] | None = None) -> list[int]:
    """The same with one task for each first bit; the evidence is broadcast, as the driver holds it anyway."""
    search = Search(sets, max_size, rivals, reduce=False)
    branches = search.branches()
    if not branches:
        return search.run()
    held = spark.sparkContext.broadcast(search)

    def run(batches):
        for pdf in batches:
            yield pd.DataFrame({"mask": [str(x) for i in pdf["id"] for x in held.value.run(*branches[int(i)])]}, dtype=object)

    return [int(r["mask"]) for r in spark.range(0, len(branches), numPartitions=len(branches)).mapInPandas(run, "mask string").collect()]


def of_rhs(evidence, rhs: int, max_size: int | None = None, most: int | None = None) -> list[int]:
    """Left sides for one right side (a bit): evidence without that difference says nothing about it."""
    return minimal([e & ~rhs for e in evidence if e & rhs], max_size, most=most)


def per_rhs(spark: SparkSession, evidence, m: int, max_size: int | None = None, where: str = "driver", most: int | None = None) -> list[tuple[int, int]]:
    """(lhs, rhs) of all minimal dependencies. where='tasks': one task for each right side; the evidence is broadcast as the driver holds it anyway."""
    if where == "driver":
        out: list[tuple[int, int]] = []
        for a in range(m):
            out += [(lhs, 1 << a) for lhs in of_rhs(evidence, 1 << a, max_size, None if most is None else most - len(out))]
        return out
    held = spark.sparkContext.broadcast(list(evidence))

    def run(batches):
        for pdf in batches:
            rows = [(str(lhs), int(a)) for a in pdf["id"] for lhs in of_rhs(held.value, 1 << int(a), max_size, most)]
            yield pd.DataFrame(rows, columns=["lhs", "rhs"])

    return [(int(r["lhs"]), 1 << r["rhs"]) for r in spark.range(0, m, numPartitions=m).mapInPandas(run, "lhs string, rhs int").collect()]


def sorted_evidence(evidence: DataFrame) -> DataFrame:
    """Evidence by number of set bits, so that small sets steer the search."""
    return evidence.withColumn("n_attrs", F.bit_count("ev0").cast("int")).orderBy("n_attrs", "ev0")
