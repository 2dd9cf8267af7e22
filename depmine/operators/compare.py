"""Evidence of all row pairs of a cell, compared in tasks by blocks of coded columns.

A cell's rows come together in one task, which codes each column by the order
of its typed values and compares blocks of rows in numpy; only distinct
evidence with its number of pairs leaves the task, so that pairs never become
rows. Where evidence says only which attributes differ, a cell of many pairs
counts them by the classes of its rows instead of one by one; where only
distinct evidence is asked for, it looks for a pair of each kind and shows of
the others that no pair can have them (`Witnesses`). Cells are
bounded: a triangle gets as many as its rows need, a cartesian product has
small blocks, the runs of a block plan are cut by its own routing.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from depmine.sources.io import materialize

from . import distribute, partition

#: Rows of one side of a triangle cell, of a cartesian block, pairs compared at once, and the size of a run that is compared by shifts.
SIDE_ROWS, BLOCK_ROWS, TILE, SHORT = 32_768, 8_192, 1 << 18, 32
#: Evidence of so many bits is counted in a table, wider evidence by sorting.
DENSE = 16
#: Rows of one side of a triangle cell and of a cartesian block whose pairs are counted by classes, up to so many attributes, where a cell has more pairs than that.
CLASS_SIDE, CLASS_BLOCK, CLASS_ATTRS, CLASS_PAIRS = 1_000_000, 1 << 18, 12, 1 << 19
#: Attributes up to which distinct evidence is found without comparing all pairs, the pairs drawn for each set of attributes, and the pairs of agreeing rows that are all compared where draws leave evidence open.
KINDS_ATTRS, DRAWN, ALL_OF = 8, 1 << 19, 1 << 25
#: Rows of a leaf of the boxes in which evidence is sought, and pairs of boxes looked at together.
LEAF, TOGETHER = 256, 1 << 14
#: Rows that a task packs at once on their way to the triangle's cells.
PACK_ROWS = 1 << 19


class Form:
    """What a pair's evidence says of each attribute. ordered: None for one bit (differs), else two bits (less, equal, greater, neither) with the orders that count."""

    def __init__(self, attrs: list[str], ordered: list[bool] | None = None):
        self.attrs, self.ordered = attrs, ordered
        self.each = 1 if ordered is None else 2
        self.bits = self.each * len(attrs)
        self.name = "ev0" if ordered is None else "code0"

    @property
    def by_classes(self) -> bool:
        """Whether pairs can be counted by classes: an attribute more doubles the sets of attributes to look at."""
        return self.ordered is None and len(self.attrs) <= CLASS_ATTRS

    @property
    def by_kinds(self) -> bool:
        """Whether distinct evidence can be sought by kinds of pairs: each attribute is compared with itself only, and in an order or not."""
        return False

    def fits(self, df: DataFrame) -> bool:
        """Whether tasks can code these attributes as Spark compares them."""
        return self.bits <= 62 and not any(isinstance(df.schema[a].dataType, (T.ArrayType, T.MapType, T.StructType, T.VariantType)) for a in self.attrs)

    def coded(self, table: pa.Table) -> list[tuple[np.ndarray, bool]]:
        """(codes in the order of the values, whether code 0 is null) of each attribute."""
        out = []
        for column, (codes, size) in zip((table.column(a) for a in self.attrs), partition.encode(table.select(self.attrs))):
            out.append((codes.astype(np.uint8 if size <= 1 << 8 else np.uint16 if size <= 1 << 16 else np.int32), column.null_count > 0))
        return out

    def evidence(self, left: list[np.ndarray], right: list[np.ndarray], nulls: list[bool]) -> np.ndarray:
        kind = np.uint8 if self.bits <= 8 else np.uint16 if self.bits <= 16 else np.int64
        total = None
        for i, (x, y, null) in enumerate(zip(left, right, nulls)):
            own = (x != y).view(np.uint8) if self.ordered is None else outcomes(x, y, self.ordered[i], null)
            own = own.astype(kind, copy=False) << kind(self.each * i)
            if total is None:
                total = own
            else:
                total |= own
        return total


def outcomes(x: np.ndarray, y: np.ndarray, ordered: bool, null: bool) -> np.ndarray:
    """Less, equal, greater, neither of codes; null: code 0 stands for it."""
    if not ordered:
        return (x != y).view(np.uint8) * np.uint8(2) + np.uint8(1)
    own = (x >= y).view(np.uint8) + (x > y).view(np.uint8)
    if null:
        own[(x == 0) != (y == 0)] = 3
    return own


class SlotForm(Form):
    """The outcomes of the slots of a predicate space, of which the first are the attributes' own; others compare two attributes, of both rows or of one."""

    def __init__(self, slots, own: int):
        super().__init__([s.left[1] for s in slots[:own]], [s.ordered for s in slots])
        self.slots, self.bits = slots, 2 * len(slots)
        self.both = sorted({(s.left[1], s.right[1]) for s in slots[own:]})
        place = {a: (i, i) for i, a in enumerate(self.attrs)} | {p: (own + 2 * i, own + 2 * i + 1) for i, p in enumerate(self.both)}
        self.ends = [place[s.left[1] if n < own else (s.left[1], s.right[1])] for n, s in enumerate(slots)]

    @property
    def by_kinds(self) -> bool:
        return len(self.slots) == len(self.attrs) <= KINDS_ATTRS

    def fits(self, df: DataFrame) -> bool:
        def alike(a, b):
            kinds = {df.schema[a].dataType.simpleString(), df.schema[b].dataType.simpleString()}
            return len(kinds) == 1 or kinds <= {"tinyint", "smallint", "int", "bigint", "double"}

        return super().fits(df) and all(alike(*p) for p in self.both)

    def coded(self, table: pa.Table) -> list[tuple[np.ndarray, bool]]:
        """Codes of each attribute, then for each two attributes compared the codes of both in one order."""
        out = super().coded(table)
        for p in self.both:
            columns = [table.column(a) for a in p]
            if columns[0].type != columns[1].type:
                kind = pa.float64() if any(pa.types.is_floating(c.type) for c in columns) else pa.int64()
                columns = [c.cast(kind, safe=False) for c in columns]
            ((codes, _),) = partition.encode(pa.table([pa.chunked_array([x for c in columns for x in c.chunks], columns[0].type)], names=["v"]))
            null = any(c.null_count for c in columns)
            out += [(codes[: len(table)], null), (codes[len(table) :], null)]
        return out

    def evidence(self, left: list[np.ndarray], right: list[np.ndarray], nulls: list[bool]) -> np.ndarray:
        kind = np.uint8 if self.bits <= 8 else np.uint16 if self.bits <= 16 else np.int64
        total = None
        for i, (slot, (a, b)) in enumerate(zip(self.slots, self.ends)):
            x, y = (left if slot.left[0] == 1 else right)[a], (left if slot.right[0] == 1 else right)[b]
            own = outcomes(x, y, slot.ordered, nulls[a]).astype(kind, copy=False) << kind(2 * i)
            if total is None:
                total = own
            else:
                total |= own
        return total


class Tally:
    """Distinct evidence and its number of pairs."""

    def __init__(self, bits: int):
        self.bits, self.many = bits, {}
        self.table = np.zeros(1 << (16 if bits <= 8 else bits), np.int64) if bits <= DENSE else None

    def add(self, seen: np.ndarray) -> None:
        seen = np.ascontiguousarray(seen).ravel()
        if self.table is None:
            values, counts = np.unique(seen, return_counts=True)
            for v, n in zip(values.tolist(), counts.tolist()):
                self.many[v] = self.many.get(v, 0) + n
        elif self.bits <= 8:  # two pairs at once
            if len(seen) % 2:
                self.many[int(seen[-1])] = self.many.get(int(seen[-1]), 0) + 1
            self.table += np.bincount(seen[: len(seen) // 2 * 2].view(np.uint16), minlength=1 << 16)
        else:
            self.table += np.bincount(seen, minlength=len(self.table))

    def put(self, value: int, pairs: int) -> None:
        self.many[value] = self.many.get(value, 0) + pairs

    def items(self) -> dict[int, int]:
        out = dict(self.many)
        if self.table is not None:
            both = self.table.reshape(1 << 8, 1 << 8) if self.bits <= 8 else None
            counts = self.table if both is None else both.sum(axis=0) + both.sum(axis=1)
            for v in np.flatnonzero(counts).tolist():
                out[v] = out.get(v, 0) + int(counts[v])
        return out

    def batch(self, name: str) -> pa.RecordBatch:
        found = self.items()
        return pa.RecordBatch.from_arrays([pa.array(list(found), pa.int64()), pa.array(list(found.values()), pa.int64())], [name, "n_pairs"])


def many(pairs: int, rows: int, form: Form) -> bool:
    """Whether classes of rows are counted in less time than pairs are compared."""
    return form.by_classes and pairs > max(CLASS_PAIRS, rows << len(form.attrs))


def counted(codes: list[np.ndarray], left: np.ndarray | None, tally: Tally) -> None:
    """All pairs of rows that are left with rows that are not, or of different rows of one list, by what they differ in.

    Rows equal on a set of attributes form a class, and its size tells how many
    pairs agree on the set at least; pairs that agree on exactly the set follow by taking off
    those that agree on more. A row that meets no other in its class goes, so larger sets are looked at with ever fewer rows.
    """
    m, n = len(codes), len(codes[0])
    sizes = [int(c.max(initial=0)) + 1 for c in codes]
    order = sorted(range(m), key=lambda i: -sizes[i])  # the most values first: its sets lose most rows
    agreeing = np.zeros(1 << m, np.int64)
    agreeing[0] = n * (n - 1) // 2 if left is None else int(left.sum()) * int(n - left.sum())

    def visit(mask: int, start: int, rows: np.ndarray | None, number: np.ndarray | None, classes: int, first: np.ndarray | None) -> None:
        for at in range(start, m):
            i = order[at]
            key = codes[i].astype(np.int64) if rows is None else number * np.int64(sizes[i]) + codes[i][rows]
            if classes * sizes[i] > 4 * len(key) + 1_024:
                values, key = np.unique(key, return_inverse=True)
                bound = len(values)
            else:
                bound = classes * sizes[i]
            if first is None:
                count = np.bincount(key, minlength=bound)
                met, pairs = count > 1, int((count * (count - 1) // 2).sum())
            else:
                mine, other = np.bincount(key[first], minlength=bound), np.bincount(key[~first], minlength=bound)
                met, pairs = (mine > 0) & (other > 0), int((mine * other).sum())
            if not pairs:
                continue
            agreeing[mask | 1 << i] = pairs
            if at + 1 < m:
                fit = met[key]
                own = np.flatnonzero(fit).astype(np.int32) if rows is None else rows[fit]
                visit(mask | 1 << i, at + 1, own, (np.cumsum(met, dtype=np.int64) - 1)[key[fit]], int(met.sum()), None if first is None else first[fit])

    visit(0, 0, None, None, 1, left)
    for i in range(m):
        both = agreeing.reshape(-1, 2, 1 << i)
        both[:, 0] -= both[:, 1]
    for mask in np.flatnonzero(agreeing).tolist():
        tally.put((1 << m) - 1 & ~mask, int(agreeing[mask]))


def across(left: list[np.ndarray], right: list[np.ndarray], nulls: list[bool], form: Form, tally: Tally) -> None:
    """All pairs of two lists of rows."""
    n, m = len(left[0]), len(right[0])
    if many(n * m, n + m, form):
        counted([np.concatenate(c) for c in zip(left, right)], np.arange(n + m) < n, tally)
        return
    for b in range(0, m, BLOCK_ROWS):
        own = [c[None, b : b + BLOCK_ROWS] for c in right]
        step = max(1, TILE // max(1, own[0].shape[1]))
        for a in range(0, n, step):
            tally.add(form.evidence([c[a : a + step, None] for c in left], own, nulls))


def among(rows: list[np.ndarray], nulls: list[bool], form: Form, tally: Tally) -> None:
    """All pairs of different rows of one list, once each."""
    n, step = len(rows[0]), 128
    if many(n * (n - 1) // 2, n, form):
        counted(rows, None, tally)
        return
    for a in range(0, n, step):
        own = [c[a : a + step] for c in rows]
        i, j = np.triu_indices(len(own[0]), 1)
        tally.add(form.evidence([c[i] for c in own], [c[j] for c in own], nulls))
        if a + step < n:
            across(own, [c[a + step :] for c in rows], nulls, form, tally)


class Boxes:
    """Rows in a binary tree of halves, with the least and the greatest code of each attribute in each node."""

    def __init__(self, codes: np.ndarray, rows: np.ndarray):
        self.rows, self.codes = rows.copy(), codes
        wide = np.maximum(codes.max(axis=0).astype(np.int64), 1)
        start, end, low, high, children = [0], [len(rows)], [], [], []
        at = 0
        while at < len(start):
            a, b = start[at], end[at]
            own = codes[self.rows[a:b]]
            lo, hi = own.min(axis=0), own.max(axis=0)
            low.append(lo)
            high.append(hi)
            if b - a <= LEAF:
                children.append(-1)
            else:
                spread = hi.astype(np.int64) - lo
                by = 0 if spread[0] else int(np.argmax(spread / wide))  # rows of one class come together first
                half = (b - a) // 2
                self.rows[a:b] = self.rows[a:b][np.argpartition(own[:, by], half)]
                children.append(len(start))
                start += [a, a + half]
                end += [a + half, b]
            at += 1
        self.start, self.end, self.children = (np.array(x, np.int64) for x in (start, end, children))
        self.low, self.high = np.array(low), np.array(high)


class Witnesses:
    """The distinct evidence of all pairs of rows that are left with rows that are not, or of different rows of one list.

    For each set of attributes on which pairs agree, pairs of its classes are
    drawn; they are all compared where they are few. Evidence that no draw
    has shown is left out only if two of its comparisons never meet, by running extremes, or if no two
    boxes of rows can hold a pair with it. Evidence is known as well by the same two rows in the other order.
    """

    def __init__(self, codes: list[np.ndarray], nulls: list[bool], left: np.ndarray | None, form: SlotForm):
        self.codes, self.nulls, self.left, self.form = codes, nulls, left, form
        self.m, self.n = len(codes), len(codes[0])
        self.known: set[int] = set()
        self.never: dict[int, set[tuple[int, int, int, int]]] = {}
        self.same = sum(1 << 2 * i for i in range(self.m))
        self.draw = np.random.default_rng(42)

    def run(self) -> set[int]:
        sizes = [int(c.max(initial=0)) + 1 for c in self.codes]
        self.order, self.sizes = sorted(range(self.m), key=lambda i: -sizes[i]), sizes
        rows = np.arange(self.n, dtype=np.int32)
        if not self._settled(0, rows, np.zeros(self.n, np.int64), 1):
            self._visit(0, 0, rows, np.zeros(self.n, np.int64), 1)
        return self.known

    def _visit(self, mask: int, start: int, rows: np.ndarray, number: np.ndarray, classes: int) -> None:
        for at in range(start, self.m):
            i = self.order[at]
            key, bound = number * np.int64(self.sizes[i]) + self.codes[i][rows], classes * self.sizes[i]
            if bound > 4 * len(key) + 1_024:
                values, key = np.unique(key, return_inverse=True)
                bound = len(values)
            if self.left is None:
                met = np.bincount(key, minlength=bound) > 1
            else:
                first = self.left[rows]
                met = (np.bincount(key[first], minlength=bound) > 0) & (np.bincount(key[~first], minlength=bound) > 0)
            fit = met[key]
            if not fit.any():
                continue
            own, kept = rows[fit], (np.cumsum(met, dtype=np.int64) - 1)[key[fit]]
            del key, fit
            if not self._settled(mask | 1 << i, own, kept, int(met.sum())) and at + 1 < self.m:
                self._visit(mask | 1 << i, at + 1, own, kept, int(met.sum()))

    def _open(self, mask: int) -> list[int]:
        """Evidence, in both orders of its rows, of agreement on exactly the set that is not known yet."""
        out = [0]
        for i in range(self.m):
            kinds = (1,) if mask >> i & 1 else (3,) if not self.form.ordered[i] else (0, 2, 3) if self.nulls[i] else (0, 2)
            out = [c | v << 2 * i for c in out for v in kinds]
        never = {p for below, found in self.never.items() if below & mask == below for p in found}
        held = lambda c: any(c >> 2 * i & 3 == x and c >> 2 * j & 3 == y for i, x, j, y in never)
        return [c for c in out if c != self.same and c not in self.known and self._turned(c) not in self.known and not held(c)]

    def _met(self, i: int, x: int, j: int, y: int, mine: np.ndarray, other: np.ndarray, number: np.ndarray) -> bool:
        """Whether two rows of a class are less (0) or greater (2) on attribute i and on attribute j, as far as codes tell: the least or greatest of j among the rows before."""
        sided = lambda rows, a, op: self.codes[a][rows].astype(np.int64) if op == 0 else self.sizes[a] - 1 - self.codes[a][rows].astype(np.int64)
        key, value = (number[r] * np.int64(self.sizes[i]) + sided(r, i, x) for r in (mine, other)), (sided(r, j, y) - number[r] * np.int64(self.sizes[j]) for r in (mine, other))
        (own, its), (low, high) = key, value
        by = np.argsort(own)
        least = np.minimum.accumulate(low[by])  # that of a class is below all of the classes before
        place = np.searchsorted(own[by], its, side="left")
        return bool((least[np.maximum(place - 1, 0)] < high)[place > 0].any())

    def _ruled_out(self, mask: int, rows: np.ndarray, number: np.ndarray) -> None:
        """Notes comparisons of two attributes that no two rows agreeing on the set have together."""
        place = np.zeros(self.n, np.int64)
        place[rows] = number
        mine, other = (rows, rows) if self.left is None else (rows[self.left[rows]], rows[~self.left[rows]])
        asked = {(i, a, j, b) for c in self._open(mask) for j in range(self.m) for i in range(j) for a, b in ((c >> 2 * i & 3, c >> 2 * j & 3),) if a in (0, 2) and b in (0, 2)}
        self.never[mask] = {p for p in sorted(asked) if not self._met(*p, mine, other, place)}

    def _turned(self, code: int) -> int:
        return sum(((0, 2)[v == 0] if v in (0, 2) else v) << 2 * i for i in range(self.m) for v in (code >> 2 * i & 3,))

    def _learn(self, left: np.ndarray, right: np.ndarray) -> None:
        """Compares rows; a row with itself shows nothing."""
        tally = Tally(self.form.bits)
        tally.add(self.form.evidence([c[left] for c in self.codes], [c[right] for c in self.codes], self.nulls))
        self.known |= set(tally.items()) - {self.same}

    def _settled(self, mask: int, rows: np.ndarray, number: np.ndarray, classes: int) -> bool:
        """Learns all evidence of pairs that agree on exactly the set. Whether that of larger sets is then known too."""
        if self.left is None:
            count = again = np.bincount(number, minlength=classes)
        else:
            first = self.left[rows]
            count, again = np.bincount(number[first], minlength=classes), np.bincount(number[~first], minlength=classes)
        ends = np.cumsum(count * again)
        total = int(ends[-1])
        if total > DRAWN and not self._open(mask):
            return False
        by = np.argsort(number, kind="stable") if mask else np.arange(len(rows))
        mine = other = rows[by]
        if self.left is not None:
            mine, other = mine[first[by]], other[~first[by]]
        begin, from_left, from_right = ends - count * again, np.cumsum(count) - count, np.cumsum(again) - again

        def compare(numbers: np.ndarray) -> None:
            c = np.searchsorted(ends, numbers, side="right") if classes > 1 else np.zeros(len(numbers), np.int64)
            place = numbers - begin[c]
            self._learn(mine[from_left[c] + place // again[c]], other[from_right[c] + place % again[c]])

        def compare_all() -> bool:
            for at in range(0, total, DRAWN):
                compare(np.arange(at, min(total, at + DRAWN)))
            return True

        if total <= DRAWN:
            return compare_all()
        compare(self.draw.integers(0, total, DRAWN))
        if self._open(mask):
            if total <= ALL_OF:
                return compare_all()
            self._ruled_out(mask, rows, number)
            if self._open(mask):
                self._sought(mask, rows, number)
        return False

    def _sought(self, mask: int, rows: np.ndarray, number: np.ndarray) -> None:
        """Open evidence of agreement on exactly the set, in boxes of rows: two boxes are taken apart as long as their extremes allow it, and their rows compared in the end."""
        targets = self._open(mask)
        table = np.zeros((self.n, self.m + 1), np.int32)
        table[rows, 0] = number
        for i, c in enumerate(self.codes):
            table[:, i + 1] = c
        a = Boxes(table, rows if self.left is None else rows[self.left[rows]])
        b = a if self.left is None else Boxes(table, rows[~self.left[rows]])
        todo = [(np.zeros(1, np.int64), np.zeros(1, np.int64))]
        while todo and targets:
            x, y = todo.pop()
            if len(x) > TOGETHER:
                todo.append((x[TOGETHER:], y[TOGETHER:]))
                x, y = x[:TOGETHER], y[:TOGETHER]
            fit = self._possible(targets, a.low[x], a.high[x], b.low[y], b.high[y])
            x, y = x[fit], y[fit]
            leaf = (a.children[x] < 0) & (b.children[y] < 0)
            for p, q in zip(x[leaf].tolist(), y[leaf].tolist()):
                if self._possible(targets, a.low[p : p + 1], a.high[p : p + 1], b.low[q : q + 1], b.high[q : q + 1])[0]:
                    before = len(self.known)
                    mine, other = a.rows[a.start[p] : a.end[p]], b.rows[b.start[q] : b.end[q]]
                    self._learn(np.repeat(mine, len(other)), np.tile(other, len(mine)))
                    if len(self.known) > before and not (targets := self._open(mask)):
                        return
            x, y = x[~leaf], y[~leaf]
            if len(x):
                one = (b.children[y] < 0) | ((a.children[x] >= 0) & (a.end[x] - a.start[x] >= b.end[y] - b.start[y]))
                down, over = a.children[x[one]], b.children[y[~one]]
                todo.append((np.concatenate([down, down + 1, x[~one], x[~one]]), np.concatenate([y[one], y[one], over, over + 1])))

    def _possible(self, targets: list[int], low: np.ndarray, high: np.ndarray, other_low: np.ndarray, other_high: np.ndarray) -> np.ndarray:
        """Whether the extremes of two boxes allow any of the targets; attribute 0 is the class, on which rows agree."""
        equal = (low <= other_high) & (high >= other_low)
        can = {1: equal, 0: low < other_high, 2: high > other_low, 3: ~((low == high) & (other_low == other_high) & (low == other_low))}
        any_of = np.zeros(len(low), bool)
        for code in targets:
            one = equal[:, 0].copy()
            for i in range(self.m):
                one &= can[code >> 2 * i & 3][:, i + 1]
            any_of |= one
        return any_of


def all_pairs(table: pa.Table, form: Form) -> dict[int, int]:
    """The evidence of a whole relation in one task."""
    tally = Tally(form.bits)
    if table.num_rows:
        coded = form.coded(table)
        among([c for c, _ in coded], [n for _, n in coded], form, tally)
    return tally.items()


def _cell(table: pa.Table, form: Form, tally: Tally) -> None:
    """One cell: rows whose anchor comes first against those whose anchor comes last; in a cell of one anchor these are the same rows."""
    _compared(form.coded(table), table.column("_a").to_numpy(), table.column("_o").to_numpy(), form, tally)


def _compared(coded: list[tuple[np.ndarray, bool]], a: np.ndarray, o: np.ndarray, form: Form, tally: Tally) -> None:
    codes, nulls = [c for c, _ in coded], [n for _, n in coded]
    first, last = a <= o, a >= o
    if (first & last).all():
        among(codes, nulls, form, tally)
    else:
        across([c[first] for c in codes], [c[last] for c in codes], nulls, form, tally)


def _summed(found: DataFrame, name: str) -> DataFrame:
    return found.groupBy(name).agg(F.sum("n_pairs").cast("long").alias("n_pairs"))


def packed(table: pa.Table) -> bytes:
    """Rows as one compressed value; texts that repeat are written once."""
    columns = []
    for c in table.columns:
        if pa.types.is_string(c.type) or pa.types.is_large_string(c.type):
            coded = c.combine_chunks().dictionary_encode()
            c = coded if 2 * len(coded.dictionary) <= len(c) else c
        columns.append(c)
    out, sink = pa.table(columns, names=table.column_names), pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, out.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as writer:
        writer.write_table(out)
    return sink.getvalue().to_pybytes()


def unpacked(value: bytes) -> pa.Table:
    table = pa.ipc.open_stream(value).read_all()
    return pa.table([c.cast(c.type.value_type) if pa.types.is_dictionary(c.type) else c for c in table.columns], names=table.column_names)


def _packing(side: int):
    """Rows of (_block, attributes) as (_block, rows) with many rows in one value."""

    def run(batches):
        held, size = [], 0
        for b in _ended(batches):
            if b is not None:
                held.append(b)
                size += b.num_rows
                if size < PACK_ROWS:
                    continue
            if not size:
                continue
            whole = pa.Table.from_batches(held)
            block = whole.column(0).to_numpy()
            made = [(x, packed(whole.select(whole.column_names[1:]).take(pa.array(at)))) for x in range(side) if len(at := np.flatnonzero(block == x))]
            yield pa.RecordBatch.from_arrays([pa.array([x for x, _ in made], pa.int32()), pa.array([v for _, v in made], pa.binary())], ["_block", "rows"])
            held, size = [], 0

    return run


def triangle(rows: DataFrame, n: int, k: int, order: list[str], form: Form, distinct: bool = False) -> DataFrame:
    """(evidence, n_pairs) of every unordered pair of rows: the triangle, with more cells than k where a cell would outgrow a task. Rows reach their cells packed.

    distinct: of more rows than a cell compares one by one only which evidence there is, in either order of a pair's rows; n_pairs is then null."""
    distinct = distinct and form.by_kinds and n > SIDE_ROWS
    whole = form.by_classes or distinct
    side = max(distribute.triangle_side(k), -(-n // CLASS_SIDE)) if whole else max(distribute.triangle_side(k), min(8, -(-n // 4_096)), -(-n // SIDE_ROWS))
    cells = side * (side + 1) // 2

    def run(table):
        tally = Tally(form.bits)
        parts = [unpacked(v) for v in table.column("rows").to_pylist()]
        a, o = (np.repeat(table.column(c).to_numpy(), [len(p) for p in parts]) for c in ("_a", "_o"))
        met = pa.concat_tables(parts)
        del parts
        coded = form.coded(met)
        del met  # codes are a few bytes a value
        if distinct:
            found = sorted(Witnesses([c for c, _ in coded], [n for _, n in coded], None if (a == o).all() else a <= o, form).run())
            return pa.table([pa.array(found, pa.int64()), pa.nulls(len(found), pa.int64())], names=[form.name, "n_pairs"])
        _compared(coded, a, o, form, tally)
        return pa.Table.from_batches([tally.batch(form.name)])

    blocks = rows.select(F.pmod(F.xxhash64(*order), F.lit(side)).cast("int").alias("_block"), *form.attrs).mapInArrow(_packing(side), "_block int, rows binary")
    routed = distribute.triangle_routes(blocks, cells, order, F.col("_block")).select("cell", "_a", "_o", "rows")
    return _summed(routed.repartition(min(cells, 2_000), "cell").groupBy("cell").applyInArrow(run, f"{form.name} long, n_pairs long"), form.name)


def cartesian(rows: DataFrame, n: int, order: list[str], form: Form) -> DataFrame:
    """The same by a cartesian product of small blocks of rows, mirrors filtered: a task holds two blocks."""
    number = max(1, -(-n // (CLASS_BLOCK if form.by_classes else BLOCK_ROWS)))
    cell = F.struct(*[F.col(a).alias(f"c{i}") for i, a in enumerate(form.attrs)])
    packed = rows.select(F.pmod(F.xxhash64(*order), F.lit(number)).cast("int").alias("b"), cell.alias("r")).groupBy("b").agg(F.collect_list("r").alias("rows"))
    packed = materialize(packed, "row-blocks")
    left, right = packed.select(F.col("b").alias("x"), F.col("rows").alias("left")), packed.select(F.col("b").alias("y"), F.col("rows").alias("right"))

    def run(batches):
        tally = Tally(form.bits)
        for batch in batches:
            for i in range(batch.num_rows):
                x, y = batch.column(0)[i].as_py(), batch.column(1)[i].as_py()
                parts = [batch.column(c)[i].values for c in ((2,) if x == y else (2, 3))]
                table = pa.concat_tables([pa.table(p.flatten(), names=form.attrs).append_column("_a", pa.array(np.full(len(p), s))).append_column("_o", pa.array(np.full(len(p), s if x == y else 1 - s))) for s, p in enumerate(parts)])
                _cell(table, form, tally)
        yield tally.batch(form.name)

    met = left.repartition(min(number, 2_000), "x").join(right, F.col("x") <= F.col("y")).select("x", "y", "left", "right")
    return _summed(met.repartition(min(number * (number + 1) // 2, 2_000), "x", "y").mapInArrow(run, f"{form.name} long, n_pairs long"), form.name)


def blocks(rows: DataFrame, k: int, order: list[str], form: Form, apart: bool = False) -> DataFrame:
    """(evidence, n_pairs) of the pairs that share a value, within the classes; a pair counts once for each shared value. apart: an exchange for each attribute, so that a row is never held once for each of them."""
    if apart and len(form.attrs) > 1:
        own = [_within(rows, [a], k, order, form) for a in form.attrs]
        return _summed(reduce(DataFrame.unionByName, own), form.name)
    return _summed(_within(rows, form.attrs, k, order, form), form.name)


def _within(rows: DataFrame, by: list[str], k: int, order: list[str], form: Form) -> DataFrame:
    routed = distribute.block_routes(rows, by, k, order)
    routed = routed.select(F.xxhash64("attr", "block", "cell").alias("_key"), "attr", "block", "cell", "_a", "_o", *form.attrs)

    def run(batches):
        tally, held = Tally(form.bits), None
        for b in _ended(batches):
            if b is not None:
                held = pa.concat_tables([*([] if held is None else [held]), pa.Table.from_batches([b])])
                if held.num_rows < 100_000:
                    continue
            if held is None or not held.num_rows:
                continue
            new = _borders(held)
            starts = np.flatnonzero(new)
            cut = int(starts[-1]) if b is not None else held.num_rows  # the last run may go on
            if cut:
                _runs(held.slice(0, cut), starts[starts < cut], form, tally)
            held = held.slice(cut)
        yield tally.batch(form.name)

    whole = routed.repartition(4 * k, "_key").sortWithinPartitions("_key", "attr", "block", "cell")
    return whole.mapInArrow(run, f"{form.name} long, n_pairs long")


def _ended(batches):
    yield from batches
    yield None


def _borders(table: pa.Table) -> np.ndarray:
    """Where a row begins a new run of equal attribute, class and cell."""
    new = np.zeros(table.num_rows, bool)
    new[0] = True
    block = table.column("block").combine_chunks()
    for c in (table.column("attr"), table.column("cell"), *block.flatten()):
        v = c.to_numpy()
        new[1:] |= v[1:] != v[:-1]
    return new


def _runs(table: pa.Table, starts: np.ndarray, form: Form, tally: Tally) -> None:
    coded = form.coded(table)
    codes, nulls = [c for c, _ in coded], [n for _, n in coded]
    a, o = table.column("_a").to_numpy(), table.column("_o").to_numpy()
    sizes = np.diff(np.append(starts, table.num_rows))
    short = np.repeat((sizes <= SHORT) & np.logical_and.reduceat(a == o, starts), sizes)
    run = np.repeat(np.arange(len(starts)), sizes)
    at = np.flatnonzero(short)
    for step in range(1, min(SHORT, len(at))):
        i, j = at[:-step], at[step:]
        same = run[i] == run[j]
        if not same.any():
            break
        i, j = i[same], j[same]
        tally.add(form.evidence([c[i] for c in codes], [c[j] for c in codes], nulls))
    for s, size in zip(starts.tolist(), sizes.tolist()):
        if short[s] or size < 2:
            continue
        own = slice(s, s + size)
        first, last = a[own] <= o[own], a[own] >= o[own]
        mine = [c[own] for c in codes]
        if (first & last).all():
            among(mine, nulls, form, tally)
        else:
            across([c[first] for c in mine], [c[last] for c in mine], nulls, form, tally)
