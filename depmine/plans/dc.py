"""Denial constraints from row pairs, by all pairs or by a sample that violations complete.

A constraint says of every two different rows that not all of its predicates
hold. Every pair counts, also one whose rows agree nowhere, so the reuse plan
forms the pairs within classes by blocks and the others by the triangle; a
pair is compared in one order and its mirror is derived.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from depmine.functions.bits import members
from depmine.operators import compare, cover, distribute, evidence
from depmine.operators.predicates import FLIP, WEAKER, Space, space_of
from depmine.sources.io import materialize

from . import hybrid, pairs
from .result import Meter

#: Ranges of an ordering's attribute when pairs are sought by it, and pairs up to which a search for violations compares all at once.
RANGES, AT_ONCE = 64, 2_000_000_000


def _own(rows: DataFrame, space: Space) -> set[int]:
    """Evidence of repeated rows with their like."""
    twice = rows.where("_m > 1").drop("_m")
    both = twice.select(*[F.col(c).alias(f"{p}_{c}") for p in "lr" for c in twice.columns])
    return set(evidence.masks(evidence.histogram(both, space.codes())))


def _seen(met: DataFrame, space: Space) -> dict[int, int]:
    return evidence.masks(evidence.histogram(met, space.codes()))


def run_pairs(df: DataFrame, attrs: list[str], plan: str, memory: str, k: int, max_predicates: int, meter: Meter, max_pairs: int | None = None, covers_in: str = "driver", **space_options) -> list[str]:
    """All pairs, or a refusal beyond max_pairs where a limit is given. Pairs are compared in tasks by blocks; those of types that tasks cannot code meet as rows."""
    with meter.phase("rest"):
        space = space_of(df, attrs, **space_options)
        rows, repeated, n = pairs.compacted(df, attrs, multiplicity=True)
        total = pairs.guard(n * (n - 1) // 2, max_pairs)
    with meter.phase("data"):
        bare = rows.drop("_m")
        form = compare.SlotForm(space.slots, len(attrs))
        coded = form.fits(bare)
        if coded:
            codes = set(evidence.masks(pairs.evidence_of(bare, n, attrs, plan, memory, k, form=form, distinct=True)))
        else:
            codes = set(_seen(pairs.pairs_of(bare, attrs, plan, memory, k), space))
        codes |= _own(rows, space) if repeated else set()
        if plan == "reuse" and coded:
            rest = evidence.masks(compare.triangle(bare, n, k, pairs.ORDER, form))
            codes |= {c for c in rest if all(space.outcome(c, i) != 1 for i in range(len(attrs)))}
        elif plan == "reuse":
            rest = distribute.triangle(bare, k, pairs.ORDER)
            for a in attrs:
                rest = rest.where(~F.col(f"l_{a}").eqNullSafe(F.col(f"r_{a}")))
            codes |= set(_seen(rest, space))
        codes |= {space.mirrored(c) for c in codes}
    meter.step("data", 1, len(codes), 0, total)
    with meter.phase("covers"):
        return [space.spelled(q) for q in constraints(codes, space, max_predicates, df.sparkSession if covers_in == "tasks" else None)]


def constraints(codes, space: Space, max_predicates: int, spark=None) -> list[tuple[tuple[int, str], ...]]:
    """Minimal constraints of at most max_predicates predicates that this evidence, closed under mirrors, does not violate: none whose predicates can be dropped or weakened, of mirrors one, and none that no rows could violate."""
    sets = {space.unsatisfied(c) for c in codes}
    search = cover.Search(sets, max_predicates, space.rivals, reduce=False)
    masks = cover.minimal_in_tasks(spark, sets, max_predicates, space.rivals) if spark else search.run()
    out = {}
    for mask in masks:
        weaker = (mask ^ 1 << i | 1 << space.place[space.predicates[i][0], w] for i in members(mask) for w in WEAKER[space.predicates[i][1]] if w in space.slots[space.predicates[i][0]].ops)
        if any(search.covers(x) for x in weaker):
            continue
        q = tuple(sorted(space.predicates[i] for i in members(mask)))
        if not space.impossible(q):
            out[min(space.spelled(q), space.spelled(space.mirror(q)))] = min(q, space.mirror(q), key=space.spelled)
    return [out[t] for t in sorted(out, key=lambda t: (t.count(" and "), t))]


def run_hybrid(df: DataFrame, attrs: list[str], plan: str, memory: str, k: int, max_predicates: int, meter: Meter, violation_rate: float = 0.0005, seed: int = 42, max_pairs: int = 5_000_000_000, max_round_pairs: int = 20_000_000, covers_in: str = "driver", **space_options) -> list[str]:
    """Sampled evidence until new evidence gets rare, its covers, then the pairs that violate a candidate, until none does. max_pairs bounds what a search for violations compares."""
    spark = df.sparkSession
    with meter.phase("rest"):
        space = space_of(df, attrs, **space_options)
        rows, repeated, n = pairs.compacted(df, attrs, multiplicity=True)
        codes = _own(rows, space) if repeated else set()
        rows = rows.drop("_m")
    groups = hybrid.group_number(n, k, k if memory == "resident" else 2 * k, max_round_pairs)
    rounds = hybrid.GroupRounds(rows, n, len(attrs), k, groups, seed, 1, 1) if plan == "rescan" else hybrid.FocusedRounds(rows, attrs, "lead" if memory == "resident" else "join", k)
    codes |= {space.mirrored(c) for c in codes}

    def learn(got: dict[int, int]) -> int:
        fresh = set(got) - codes
        codes.update(fresh, (space.mirrored(c) for c in fresh))
        return len(fresh)

    with meter.phase("data"):
        while n > 1 and (sample := rounds.next()):
            got = _seen(sample[1], space)
            fresh, compared = learn(got), sum(got.values())
            meter.step("data", rounds.rounds, len(codes), fresh, compared)
            if plan == "reuse":
                if not rounds.learned(sample[0], fresh, compared):
                    break
            elif not compared or fresh / compared < violation_rate:
                break
    search = Violations(rows, n, attrs, space, max_pairs, k)
    while True:
        with meter.phase("covers"):
            found = constraints(codes, space, max_predicates, spark if covers_in == "tasks" else None)
        with meter.phase("schema"):
            fresh = learn(search.near(found)) if found and n > 1 and not search.few_pairs else 0
            if not fresh and found and n > 1:
                fresh = learn(search.all(found))
        meter.step("schema", 1, len(found), fresh)
        if not fresh:
            return [space.spelled(q) for q in found]


class Violations:
    """Evidence of pairs that violate a candidate."""

    def __init__(self, rows: DataFrame, n: int, attrs: list[str], space: Space, max_pairs: int, k: int = 8):
        self.rows, self.n, self.attrs, self.space, self.max_pairs, self.k = rows, n, attrs, space, max_pairs, k
        self.form = compare.SlotForm(space.slots, len(attrs))
        self.few_pairs = n * (n - 1) // 2 <= min(AT_ONCE, max_pairs) and self.form.fits(rows)
        self.compared = False
        self.few: DataFrame | None = None
        self.edges: dict[tuple[str, ...], list] = {}

    def _any(self, group) -> Column:
        """Whether a pair violates one of the candidates in the order given, or a mirror of one."""
        held = [self.space.condition(q) for q in group] or [F.lit(False)]
        while len(held) > 1:  # as a balanced tree: a chain of hundreds is too deep for the analyzer
            held = [a | b for a, b in zip(held[::2], held[1::2])] + held[len(held) // 2 * 2 :]
        return held[0]

    def pivots(self) -> DataFrame:
        """At most 32 rows and two a attribute: by hash, and those with the least and the greatest value."""
        if self.few is None:
            whole = F.struct(*[F.col(c) for c in self.rows.columns])
            ends = self.rows.agg(*[f(whole, F.col(a)).alias(f"{n}{i}") for i, a in enumerate(self.attrs) for n, f in (("lo", F.min_by), ("hi", F.max_by))])
            far = ends.select(F.explode(F.array(*[F.col(f"{n}{i}") for i in range(len(self.attrs)) for n in ("lo", "hi")])).alias("r")).where("r is not null").select("r.*")
            near = self.rows.orderBy(*pairs.ORDER).limit(32)
            self.few = materialize(near.unionByName(far).distinct(), "pivots")
        return self.few

    def near(self, found) -> dict[int, int]:
        """Violations with one of the pivot rows: a cheap pass that refutes most wrong candidates."""
        left, right = distribute.sided(F.broadcast(self.pivots()), "l_"), distribute.sided(self.rows, "r_")  # at most 32 + 2 m rows
        differ = (F.col("l__h1") != F.col("r__h1")) | (F.col("l__h2") != F.col("r__h2"))
        both = [*found, *map(self.space.mirror, found)]
        return _seen(right.join(left, differ & self._any(both)), self.space)

    def all(self, found) -> dict[int, int]:
        """All violations: pairs meet by equality where classes are small, else in ranges of an ordering that can hold a violation. Few pairs are all compared by blocks, which is one job whatever the candidates."""
        if self.few_pairs:
            if self.compared:
                return {}
            self.compared = True
            return evidence.masks(compare.triangle(self.rows, self.n, self.k, pairs.ORDER, self.form))
        groups: dict[tuple, list] = {}
        for q in found:
            keys = tuple(sorted(s for s, op in q if op == "=" and not self.space.slots[s].single))
            ranges = [(s, op) for s, op in q if op not in ("=", "!=") and not self.space.slots[s].single]
            groups.setdefault((keys, ranges[0] if ranges else None), []).append(q)
        out: dict[int, int] = {}
        for (keys, by), group in groups.items():
            if keys and (by is None or self._class_pairs(keys) <= 50 * self.n + 1_000_000):
                if by is None:
                    self._allowed(self._class_pairs(keys))
                met = self._by_keys(keys)
            elif by:
                met = self._by_ranges(by, group)
            else:
                self._allowed(self.n * (self.n - 1) // 2)
                made = distribute.triangle(self.rows, 55, pairs.ORDER)
                met = made.select(*self._sides()).unionByName(made.select(*[F.col(f"{b}_{c}").alias(f"{a}_{c}") for a, b in (("l", "r"), ("r", "l")) for c in self.rows.columns]))
            differ = (F.col("l__h1") != F.col("r__h1")) | (F.col("l__h2") != F.col("r__h2"))
            out |= _seen(met.where(differ & self._any(group)), self.space)
        return out

    def _sides(self) -> list[Column]:
        return [F.col(f"{p}_{c}") for p in "lr" for c in self.rows.columns]

    def _allowed(self, number: int) -> None:
        if number > self.max_pairs:
            raise MemoryError(f"{number} pairs to compare, more than the limit of {self.max_pairs}")

    def _operands(self, keys) -> list[tuple[str, str]]:
        """(attribute of the left row, attribute of the right row) of slots across rows."""
        out = []
        for s in keys:
            ends = dict((self.space.slots[s].left, self.space.slots[s].right))
            out.append((ends[1], ends[2]))
        return out

    def _class_pairs(self, keys) -> int:
        ends = self._operands(keys)
        left = self.rows.groupBy(*[F.col(a).alias(f"x{i}") for i, (a, _) in enumerate(ends)]).agg(F.count("*").alias("n"))
        right = self.rows.groupBy(*[F.col(b).alias(f"y{i}") for i, (_, b) in enumerate(ends)]).agg(F.count("*").alias("m"))
        same = F.lit(True)
        for i in range(len(ends)):
            same = same & F.col(f"x{i}").eqNullSafe(F.col(f"y{i}"))
        return left.join(right, same).agg(F.sum(F.col("n") * F.col("m")).alias("w")).first()["w"] or 0

    def _by_keys(self, keys) -> DataFrame:
        left, right = distribute.sided(self.rows, "l_"), distribute.sided(self.rows, "r_")
        same = F.lit(True)
        for a, b in self._operands(keys):
            same = same & F.col(f"l_{a}").eqNullSafe(F.col(f"r_{b}"))
        return left.join(right, same)

    def _borders(self, ends: tuple[str, str]) -> list:
        """Borders of ranges with about equally many values of the two attributes."""
        if ends not in self.edges:
            both = self.rows.select(F.col(ends[0]).alias("v")).unionByName(self.rows.select(F.col(ends[1]).alias("v")))
            cut = both.agg(F.percentile_approx("v", [i / RANGES for i in range(1, RANGES)], 1_000).alias("p")).first()["p"]
            self.edges[ends] = sorted(set(cut or []))
        return self.edges[ends]

    def _by_ranges(self, by: tuple[int, str], group) -> DataFrame:
        """Pairs of ranges of one ordering's attributes in which some candidate's orderings can all hold, by the extremes of both ranges; then the rows of these ranges."""
        s, op = by
        ((a, b),) = self._operands([s])
        if self.space.slots[s].left[0] == 2:
            op = FLIP[op]
        borders = self._borders((a, b))
        place = lambda c: sum((F.when(F.col(c) >= F.lit(x), 1).otherwise(0) for x in borders), F.lit(0))
        left = self.rows.where(F.col(a).isNotNull()).withColumn("range", place(a))
        right = self.rows.where(F.col(b).isNotNull()).withColumn("range", place(b))
        slots = sorted({t for q in group for t, o in q if not self.space.slots[t].single and self.space.slots[t].ordered})
        ends = {t: self._operands([t])[0] for t in slots}
        stat = lambda df, side: df.groupBy(F.col("range").alias(f"{side}_range")).agg(F.count("*").alias(f"{side}_n"), *[f(ends[t][side == "r"]).alias(f"{side}_{n}{t}") for t in slots for n, f in (("lo", F.min), ("hi", F.max))])
        can = F.lit(False)
        for q in group:
            one = F.lit(True)
            for t, o in q:
                if t in slots and o != "!=":
                    o = FLIP[o] if self.space.slots[t].left[0] == 2 else o
                    low, high = F.col(f"l_lo{t}") <= F.col(f"r_hi{t}"), F.col(f"l_hi{t}") >= F.col(f"r_lo{t}")
                    strict = F.col(f"l_lo{t}") < F.col(f"r_hi{t}") if o == "<" else F.col(f"l_hi{t}") > F.col(f"r_lo{t}") if o == ">" else low if o == "<=" else high if o == ">=" else low & high
                    one = one & (F.coalesce(strict, F.lit(False)) if o in ("<", ">") else F.coalesce(strict, F.lit(True)))
            can = can | one
        met = stat(left, "l").join(stat(right, "r"), can)  # RANGES x RANGES rows at most
        chosen = materialize(met.select("l_range", "r_range", "l_n", "r_n"), "ranges")
        self._allowed(chosen.agg(F.sum(F.col("l_n") * F.col("r_n")).alias("w")).first()["w"] or 0)
        cells = F.broadcast(chosen.select("l_range", "r_range"))
        rows = distribute.sided(left, "l_").join(cells, "l_range")
        return rows.join(distribute.sided(right, "r_"), "r_range").select(*self._sides())
