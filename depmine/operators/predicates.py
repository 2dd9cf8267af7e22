"""The predicate space of denial constraints, and the evidence of row pairs over it.

A slot compares two operands, each an attribute of the first or the second row
of a pair: the same attribute of both rows, two attributes across rows, or two
attributes of one row. A slot's outcome takes two bits: 0 less, 1 equal,
2 greater, 3 neither (a null on one side, or a type without order); `=` treats
null as a value, the ordering comparisons are false on null.
"""

from __future__ import annotations

from dataclasses import dataclass
from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from depmine.functions.prep import cells

ORDERED = (T.NumericType, T.DateType, T.TimestampType, T.TimestampNTZType)
#: Slots in one 62-bit word.
PER_WORD = 31
#: What each of the four outcomes satisfies.
SATISFIED = {0: ("!=", "<", "<="), 1: ("=", "<=", ">="), 2: ("!=", ">", ">="), 3: ("!=",)}
FLIP = {"=": "=", "!=": "!=", "<": ">", ">": "<", "<=": ">=", ">=": "<="}
#: The next weaker comparisons: whoever satisfies the first satisfies these.
WEAKER = {"=": ("<=", ">="), "<": ("<=", "!="), ">": (">=", "!="), "!=": (), "<=": (), ">=": ()}
FLIPPED = {0: 2, 1: 1, 2: 0, 3: 3}


@dataclass(frozen=True)
class Slot:
    left: tuple[int, str]  # (row of the pair, attribute)
    right: tuple[int, str]
    ordered: bool

    @property
    def ops(self) -> tuple[str, ...]:
        return ("=", "!=", "<", "<=", ">", ">=") if self.ordered else ("=", "!=")

    @property
    def single(self) -> bool:
        return self.left[0] == self.right[0]

    def spelled(self, op: str) -> str:
        return f"t{self.left[0]}.{self.left[1]} {op} t{self.right[0]}.{self.right[1]}"

    def operands(self) -> tuple[Column, Column]:
        return tuple(F.col(f"{'lr'[row - 1]}_{a}") for row, a in (self.left, self.right))


class Space:
    """Slots, their predicates (slot number, operator), and how a pair's evidence turns when its rows change places."""

    def __init__(self, slots: list[Slot]):
        self.slots = slots
        self.predicates = [(s, op) for s, slot in enumerate(slots) for op in slot.ops]
        self.place = {p: i for i, p in enumerate(self.predicates)}
        at = {(slot.left, slot.right): s for s, slot in enumerate(slots)}
        self.partner: list[tuple[int, bool]] = []
        for slot in slots:
            left, right = ((3 - row, a) for row, a in (slot.left, slot.right))
            self.partner.append((at[left, right], False) if (left, right) in at else (at[right, left], True))
        own = {s: sum(1 << self.place[s, op] for op in slot.ops) for s, slot in enumerate(slots)}
        #: Predicates of one slot exclude each other in a constraint: any two of them amount to one.
        self.rivals = {i: own[s] for i, (s, _) in enumerate(self.predicates)}
        self.satisfied = [[sum(1 << self.place[s, op] for op in SATISFIED[v] if op in slot.ops) for v in range(4)] for s, slot in enumerate(slots)]

    def codes(self) -> list[Column]:
        """The outcomes of all slots of a pair (l_*, r_*) as columns code0, code1, ... of 31 slots each."""
        out = []
        for w in range(0, max(1, len(self.slots)), PER_WORD):
            total = F.lit(0).cast("long")
            for i, slot in enumerate(self.slots[w : w + PER_WORD]):
                x, y = slot.operands()
                code = F.when(x.eqNullSafe(y), 1)
                if slot.ordered:
                    code = code.when(x < y, 0).when(x > y, 2)
                total = total + F.shiftleft(code.otherwise(3).cast("long"), 2 * i)
            out.append(total.alias(f"code{w // PER_WORD}"))
        return out

    def outcome(self, code: int, slot: int) -> int:
        return code >> 2 * slot & 3

    def mirrored(self, code: int) -> int:
        """The evidence of the same two rows in the other order."""
        out = 0
        for s, (other, flip) in enumerate(self.partner):
            v = code >> 2 * other & 3
            out |= (FLIPPED[v] if flip else v) << 2 * s
        return out

    def unsatisfied(self, code: int) -> int:
        """The predicates, as bits, that a pair with this evidence does not satisfy."""
        held = 0
        for s, by in enumerate(self.satisfied):
            held |= by[code >> 2 * s & 3]
        return (1 << len(self.predicates)) - 1 & ~held

    def mirror(self, constraint) -> tuple[tuple[int, str], ...]:
        """A constraint, as (slot, operator) pairs, with its rows exchanged."""
        turned = []
        for s, op in constraint:
            other, flip = self.partner[s]
            turned.append((other, FLIP[op] if flip else op))
        return tuple(sorted(turned))

    def spelled(self, constraint) -> str:
        return " and ".join(sorted(self.slots[s].spelled(op) for s, op in constraint))

    def condition(self, constraint) -> Column:
        """Whether a pair (l_*, r_*) satisfies all predicates, that is, violates the constraint."""
        held = F.lit(True)
        for s, op in constraint:
            held = held & compared(*self.slots[s].operands(), op)
        return held

    def impossible(self, constraint) -> bool:
        """Whether no pair of any relation satisfies it: the comparisons chain into a cycle that a strict one is part of."""
        nodes = {x for s, _ in constraint for x in (self.slots[s].left, self.slots[s].right)}
        reach = {(x, x) for x in nodes}
        for s, op in constraint:
            a, b = self.slots[s].left, self.slots[s].right
            reach |= {(a, b)} if op in ("<", "<=") else {(b, a)} if op in (">", ">=") else {(a, b), (b, a)} if op == "=" else set()
        for m in nodes:
            reach |= {(x, y) for x in nodes if (x, m) in reach for y in nodes if (m, y) in reach}
        for s, op in constraint:
            a, b = self.slots[s].left, self.slots[s].right
            if op == "<" and (b, a) in reach or op == ">" and (a, b) in reach or op == "!=" and (a, b) in reach and (b, a) in reach:
                return True
        return False


def compared(x: Column, y: Column, op: str) -> Column:
    if op in ("=", "!="):
        return x.eqNullSafe(y) if op == "=" else ~x.eqNullSafe(y)
    strict = {"<": x < y, "<=": x < y, ">": x > y, ">=": x > y}[op]
    return F.coalesce(strict, F.lit(False)) | x.eqNullSafe(y) if "=" in op else F.coalesce(strict, F.lit(False))


def _family(kind: T.DataType) -> str:
    return "number" if isinstance(kind, T.NumericType) else kind.simpleString()


def shared_values(df: DataFrame, attrs: list[str]) -> dict[tuple[str, str], float]:
    """For each two attributes of comparable types, the share of the smaller one's distinct values that the other has. One pass: the driver gets counts by set of attributes."""
    out: dict[tuple[str, str], float] = {}
    families: dict[str, list[str]] = {}
    for a in attrs:
        families.setdefault(_family(df.schema[a].dataType), []).append(a)
    for family, own in families.items():
        if len(own) < 2 or len(own) > 60:
            continue
        typed = df.select(*[F.col(a).cast("double") if family == "number" else F.col(a) for a in own])
        values, slots = cells(typed, own)
        flat = typed.select(F.explode(values).alias("c")).select("c.attr", f"c.{slots[0]}").where(F.col(slots[0]).isNotNull())
        held = flat.groupBy(slots[0]).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), F.col("attr"))).alias("mask")).groupBy("mask").agg(F.count("*").alias("n")).collect()
        n = [sum(r["n"] for r in held if r["mask"] >> i & 1) for i in range(len(own))]
        for i, j in combinations(range(len(own)), 2):
            both = sum(r["n"] for r in held if r["mask"] >> i & 1 and r["mask"] >> j & 1)
            out[own[i], own[j]] = both / max(1, min(n[i], n[j]))
    return out


def space_of(df: DataFrame, attrs: list[str], cross: bool = False, single: bool = False, overlap: float = 0.3, order_texts: bool = False) -> Space:
    """Predicates on the same attribute of both rows; with `cross` also between comparable attributes of the two rows that share at least `overlap` of their values, with `single` between such attributes of one row."""
    kinds = (*ORDERED, T.StringType) if order_texts else ORDERED
    ordered = {a: isinstance(df.schema[a].dataType, kinds) for a in attrs}
    slots = [Slot((1, a), (2, a), ordered[a]) for a in attrs]
    if cross or single:
        for (a, b), share in shared_values(df, attrs).items():
            if share >= overlap:
                both = ordered[a] and ordered[b]
                slots += [Slot((1, a), (2, b), both), Slot((1, b), (2, a), both)] if cross else []
                slots += [Slot((1, a), (1, b), both), Slot((2, a), (2, b), both)] if single else []
    return Space(slots)
