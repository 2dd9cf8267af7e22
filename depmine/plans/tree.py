"""Prefix tree of candidate dependencies: a path of attributes is a left side, a node holds the right sides valid there and reachable below."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from depmine.functions.bits import members


class Node:
    __slots__ = ("ends", "below", "children")

    def __init__(self):
        self.ends, self.below, self.children = 0, 0, {}


class CandidateTree:
    """Minimal candidates lhs -> rhs. Right sides are bits; a tree of unique combinations uses the one right side 1 << m."""

    def __init__(self, m: int, kind: str = "fd", max_lhs: int | None = None):
        self.m, self.kind, self.max_lhs = m, kind, max_lhs
        self.rhs = [1 << a for a in range(m)] if kind == "fd" else [1 << m]
        self.root = Node()
        for bit in self.rhs:
            self.insert(0, bit)

    def insert(self, lhs: int, rhs: int) -> None:
        node = self.root
        node.below |= rhs
        for i in members(lhs):
            node = node.children.setdefault(i, Node())
            node.below |= rhs
        node.ends |= rhs

    def remove(self, lhs: int, rhs: int) -> None:
        path, node = [], self.root
        for i in members(lhs):
            path.append((node, i))
            node = node.children[i]
        node.ends &= ~rhs
        for at in [node, *[n for n, _ in reversed(path)]]:
            at.below = at.ends
            for i, child in list(at.children.items()):
                if child.below:
                    at.below |= child.below
                else:
                    del at.children[i]

    def has_generalisation(self, lhs: int, rhs: int) -> bool:
        def go(node: Node, rest: int) -> bool:
            if node.ends & rhs:
                return True
            return any(rest >> i & 1 and child.below & rhs and go(child, rest) for i, child in node.children.items())

        return go(self.root, lhs)

    def within(self, allowed: int, rhs: int) -> list[int]:
        """Left sides inside `allowed` that carry this right side."""
        out = []

        def go(node: Node, lhs: int) -> None:
            if node.ends & rhs:
                out.append(lhs)
            for i, child in node.children.items():
                if allowed >> i & 1 and child.below & rhs:
                    go(child, lhs | 1 << i)

        go(self.root, 0)
        return out

    def refute(self, mask: int) -> int:
        """A pair that differs exactly in mask: remove what it refutes and put the minimal extensions that it does not. Returns how many it removed."""
        everything, gone = (1 << self.m) - 1, 0
        for rhs in self.rhs:
            if self.kind == "fd" and not mask & rhs:
                continue
            for lhs in self.within(everything & ~mask, rhs):
                self.remove(lhs, rhs)
                gone += 1
                self._extend(lhs, rhs, mask)
        return gone

    def specialise(self, lhs: int, rhs: int) -> None:
        """A candidate that failed on the data, without a pair at hand."""
        self.remove(lhs, rhs)
        self._extend(lhs, rhs, (1 << self.m) - 1)

    def _extend(self, lhs: int, rhs: int, by: int) -> None:
        if self.max_lhs is not None and lhs.bit_count() >= self.max_lhs:
            return
        for i in members(by & ~lhs & ~rhs & (1 << self.m) - 1):
            if not self.has_generalisation(lhs | 1 << i, rhs):
                self.insert(lhs | 1 << i, rhs)

    def items(self) -> list[tuple[int, int]]:
        out = []

        def go(node: Node, lhs: int) -> None:
            out.extend((lhs, rhs) for rhs in self.rhs if node.ends & rhs)
            for i, child in node.children.items():
                go(child, lhs | 1 << i)

        go(self.root, 0)
        return out

    def level(self, size: int) -> list[tuple[int, int]]:
        out = []

        def go(node: Node, lhs: int, more: int) -> None:
            if not more:
                out.extend((lhs, rhs) for rhs in self.rhs if node.ends & rhs)
                return
            for i, child in node.children.items():
                go(child, lhs | 1 << i, more - 1)

        go(self.root, 0, size)
        return out

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(str(x), str(a), x.bit_count()) for x, a in self.items()], "lhs string, rhs string, level int")
