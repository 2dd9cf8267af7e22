"""Order dependencies: constancy is a functional dependency, compatibility means no swap within the classes of a context.

The search goes level by level over the whole lattice of attribute sets. A set
X stands for the constancies X\\A: [] -> A and the compatibilities
X\\{A,B}: A ~ B of its members; what already holds in a smaller context is
pruned, and a set without open candidates goes with all above it.
"""

from __future__ import annotations

from functools import reduce
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from depmine.functions.bits import members, names
from depmine.operators import partition
from depmine.operators.refine import swap_flags

from . import lattice
from .result import Meter

OD = "lhs string, rhs string, direction string, kind string"
#: Contexts and leading attributes of one job, and the size from which a class is spread over tasks.
CHECKS, SPREAD = 8, 1_000_000
Question = tuple[int, int, int, bool]  # context, a, b, descending


class Rows:
    """Checks from rows (rescan, spill): one pass for each context and leading attribute answers all other attributes and both directions; CHECKS passes are one job."""

    def __init__(self, df: DataFrame, attrs: list[str]):
        self.df, self.attrs, self.largest = df, attrs, {}

    def counts(self, masks: list[int]) -> dict[int, int]:
        got = partition.class_sizes(self.df, self.attrs, masks)
        self.largest |= {m: most for m, (_, most) in got.items()}
        return {m: n for m, (n, _) in got.items()}

    def of_context(self, context: int) -> tuple[DataFrame, list[str]]:
        return self.df, [self.attrs[c] for c in members(context)]

    def swapped(self, questions: list[Question]) -> dict[Question, bool]:
        passes: dict[tuple[int, int], list[Question]] = {}
        for q in questions:
            passes.setdefault(q[:2], []).append(q)
        out = dict.fromkeys(questions, False)
        todo = list(passes.items())
        for at in range(0, len(todo), CHECKS):
            parts = []
            for n, ((context, a), own) in enumerate(todo[at : at + CHECKS]):
                df, columns = self.of_context(context)
                others = list(dict.fromkeys(b for _, _, b, _ in own))
                flags = swap_flags(df, columns, self.attrs[a], [self.attrs[b] for b in others], not columns or self.largest.get(context, 0) > SPREAD)
                asked = [F.struct(F.lit(b).alias("b"), F.lit(d).alias("d"), F.col(f"{'down' if d else 'up'}{others.index(b)}").alias("bad")) for _, _, b, d in own]
                parts.append(flags.select(F.lit(n).alias("n"), F.explode(F.filter(F.array(*asked), lambda x: x["bad"])).alias("q")).select("n", "q.b", "q.d"))
            for r in reduce(DataFrame.unionByName, parts).distinct().collect():  # at most one row for each question
                out[(*todo[at + r["n"]][0], r["b"], r["d"])] = True
        return out


class Classes(Rows):
    """Checks in stored classes (reuse): the context is the class that the lattice's store names for each row."""

    def __init__(self, held: lattice.StoredClasses, attrs: list[str]):
        super().__init__(held.rows, attrs)
        self.held = held

    def counts(self, masks: list[int]) -> dict[int, int]:
        got = self.held.counts(masks)
        self.largest |= {x: most for x, (_, most) in self.held.sizes.items()}
        return got

    def of_context(self, context: int) -> tuple[DataFrame, list[str]]:
        stored = self.held.with_classes(context) if context else None
        return (self.held.rows, [self.attrs[c] for c in members(context)]) if stored is None else (stored, ["class_id"])


class Codes:
    """Checks on the broadcast codes (rescan, resident), dealt to the workers."""

    def __init__(self, held: partition.BroadcastCodes):
        self.held, self.counts = held, held.counts

    def swapped(self, questions: list[Question]) -> dict[Question, bool]:
        return {q: bool(n) for q, n in zip(questions, self.held.answer(questions, partition.swapped))}


def checker(df: DataFrame, attrs: list[str], plan: str, memory: str, k: int, meter: Meter | None = None):
    if plan == "reuse":
        return Classes(lattice.StoredClasses(df, attrs, memory, k, meter=meter, keep=3), attrs)
    if memory == "resident":
        held = partition.BroadcastCodes(df, attrs, k)
        if meter:
            meter.told(held.bytes)
        return Codes(held)
    return Rows(df, attrs)


def unary(attrs: list[str], meter: Meter, check, directions=("asc", "desc")) -> list[tuple[str, str, str, str]]:
    """a orders b: a -> b holds and a, b are compatible. One counting job, and one pass for each leading attribute."""
    bits = [1 << i for i in range(len(attrs))]
    size = check.counts(bits) | check.counts([a | b for a, b in combinations(bits, 2)])
    asked = [(0, i, j, d == "desc") for i in range(len(attrs)) for j in range(len(attrs)) if i != j and size[bits[i]] == size[bits[i] | bits[j]] for d in directions]
    with meter.phase("schema"):
        bad = check.swapped(asked) if asked else {}
    out = [(attrs[i], attrs[j], "desc" if d else "asc", "list") for q in asked if not bad[q] for _, i, j, d in [q]]
    meter.step("schema", 2, len(size), len(out))
    return out


def run(attrs: list[str], rows: int, meter: Meter, check, max_context: int | None = None, directions=("asc", "desc")) -> list[tuple[str, str, str, str]]:
    """Minimal set-based dependencies: `ctx: [] -> a` (kind constant) and `ctx: a ~ b` (kind compatible).

    Each set carries the attributes whose constancy is open and the pairs, with
    direction, whose compatibility is; a pair is left out where one side is
    constant in the context, or once it is compatible in a smaller one. max_context bounds the contexts' size.
    """
    m, everything = len(attrs), (1 << len(attrs)) - 1
    turns = [d == "desc" for d in directions]
    out: list[tuple[str, str, str, str]] = []
    constants: list[tuple[int, int]] = []
    size, open_const, open_pairs = {0: min(1, rows)}, {0: everything}, {}
    level, depth = [1 << i for i in range(m)], 1

    def constant(context: int, a: int) -> bool:
        return any(b == a and y & ~context == 0 for y, b in constants)

    while level and (max_context is None or depth <= max_context + 2):
        with meter.phase("schema"):
            size |= check.counts(level)
            fresh_const, fresh_pairs, asked = {}, {}, []
            for x in level:
                inside = members(x)
                rest = everything
                for a in inside:
                    rest &= open_const[x ^ 1 << a]
                for a in members(x & rest):
                    context = x ^ 1 << a
                    if size[context] == size[x] and (max_context is None or context.bit_count() <= max_context):
                        constants.append((context, a))
                        out.append((names(context, attrs), attrs[a], "asc", "constant"))
                        rest &= x & ~(1 << a)
                fresh_const[x] = rest
            for x in level:
                inside = members(x)
                if depth >= 2:
                    own = set()
                    for a, b in combinations(inside, 2):
                        context = x ^ 1 << a ^ 1 << b
                        if constant(context, a) or constant(context, b):
                            continue
                        for d in turns:
                            if depth == 2 or all((a, b, d) in open_pairs[x ^ 1 << c] for c in members(context)):
                                own.add((a, b, d))
                    fresh_pairs[x] = own
                    asked += [(x ^ 1 << a ^ 1 << b, a, b, d) for a, b, d in sorted(own)]
            bad = check.swapped(asked) if asked else {}
        for (context, a, b, d), swap in bad.items():
            if not swap:
                fresh_pairs[context | 1 << a | 1 << b].discard((a, b, d))
                out.append((names(context, attrs), f"{attrs[a]}~{attrs[b]}", "desc" if d else "asc", "compatible"))
        meter.step("schema", depth, len(level), len(out), len(asked))
        open_const, open_pairs = fresh_const, fresh_pairs
        level = lattice.next_level([x for x in level if depth < 2 or open_const[x] or open_pairs[x]])
        depth += 1
    return out
