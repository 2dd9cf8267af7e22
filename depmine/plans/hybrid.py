"""Hybrid search: rounds of sampled pairs refute candidates cheaply, then each level of what is left is tested on all rows.

The result never depends on when the phases change: evidence removes only what is false, and every survivor is tested exactly.
"""

from __future__ import annotations

import time
from math import ceil, sqrt

from pyspark.sql import DataFrame

from depmine.operators import distribute, evidence
from depmine.sources.io import materialize

from . import lattice, pairs
from .result import Meter
from .tree import CandidateTree


class FocusedRounds:
    """Reuse: pairs at growing distance within the classes of the attribute that paid best so far.

    `lead`: classes are dealt to the workers in bands by size. `join`: places in
    the classes are numbered once an attribute and joined at the distance.
    """

    def __init__(self, rows: DataFrame, attrs: list[str], mode: str, k: int, window: int = 1, meter: Meter | None = None):
        self.rows, self.attrs, self.mode, self.k, self.meter = rows, attrs, mode, k, meter
        self.window = dict.fromkeys(attrs, window)
        self.paid = {a: float("inf") for a in attrs}
        self.ready: dict[str, DataFrame] = {}
        self.rounds = 0

    def next(self) -> tuple[str, DataFrame] | None:
        live = [a for a in self.attrs if self.paid[a] > 0]
        if not live:
            return None
        a = max(live, key=lambda x: self.paid[x])
        order = [*[b for b in self.attrs if b != a], *pairs.ORDER]  # neighbours are alike
        if self.mode == "lead":
            routed = self.ready[a] if a in self.ready else distribute.class_routes(self.rows, a, self.k)
            sample = distribute.led(routed, a, self.window[a], order).drop("worker")
        else:
            routed = self.ready[a] if a in self.ready else materialize(distribute.positions(self.rows, [a], order), "places")
            sample = distribute.meeting(routed, a, self.window[a])
        self.ready[a] = routed
        self.window[a] += 1
        self.rounds += 1
        return a, sample

    def learned(self, a: str, refuted: int, compared: int) -> bool:
        """The attribute's rank; go on while some attribute still refutes."""
        self.paid[a] = refuted / compared if compared else 0.0
        return any(x > 0 for x in self.paid.values())


class GroupRounds:
    """Rescan: random groups, k unseen pairs of groups a round; goes on while the next round is cheaper than the next level."""

    def __init__(self, rows: DataFrame, n: int, m: int, k: int, groups: int, seed: int, alpha: float, beta: float):
        self.n, self.m, self.k, self.alpha, self.beta = n, m, k, alpha, beta
        self.rows = distribute.with_groups(rows, groups, pairs.ORDER, seed)
        self.groups = groups
        self.schedule = distribute.PairSchedule(groups, k, seed)
        self.rounds = 0

    def next(self):
        if self.rounds >= self.schedule.rounds:
            return None
        own = self.schedule.round(self.rounds)
        self.rounds += 1
        return "groups", distribute.group_pairs(self.rows, own, pairs.ORDER)

    def cost(self) -> float:
        return self.alpha * 2 * self.n * self.m / self.groups + self.beta * self.m * (self.n / self.groups) ** 2

    def learned(self, _a, refuted: int, compared: int, schema_cost: float = 0.0) -> bool:
        return refuted > 0 and self.cost() < schema_cost


def group_number(n: int, k: int, groups: int, max_round_pairs: int) -> int:
    """At least `groups`, and so many that a round of k pairs of groups compares at most max_round_pairs rows."""
    return max(groups, ceil(n * sqrt(k / max_round_pairs)))


def schema_cost(n: int, m: int, k: int, level: int, cached: bool, alpha: float, beta: float) -> float:
    return alpha * (0 if cached else n * m) + beta * level * n * m / k


def run(df: DataFrame, attrs: list[str], kind: str, plan: str, memory: str, k: int, max_lhs: int | None, meter: Meter, data_phase: bool = True, max_rounds: int | None = None, groups: int | None = None, seed: int = 42, alpha: float = 1.0, beta: float = 1.0, max_round_pairs: int = 20_000_000, prune_keys: bool = False, level_budget: float | None = None, max_candidates: int | None = None) -> list[tuple[int, int]]:
    """kind: fd or ucc. prune_keys: a left side known to be a key needs no test for its right sides. max_candidates: refuse a level of more."""
    m = len(attrs)
    if memory == "resident":  # refuses before any round
        with meter.phase("schema"):
            count, _ = lattice.counter_for(df, attrs, "rescan", memory, k, meter=meter)
    with meter.phase("rest"):
        rows, repeated, n = pairs.compacted(df, attrs)
    if kind == "ucc" and repeated:
        return []
    tree = CandidateTree(m, kind, max_lhs)
    groups = group_number(n, k, groups or (k if memory == "resident" else 2 * k), max_round_pairs)
    rounds = GroupRounds(rows, n, m, k, groups, seed, alpha, beta) if plan == "rescan" else FocusedRounds(rows, attrs, "lead" if memory == "resident" else "join", k)
    seen: set[int] = set()
    spent = 0.0

    def data_rounds() -> None:
        nonlocal spent
        going = True
        while going and (max_rounds is None or rounds.rounds < max_rounds) and (sample := rounds.next()):
            at = time.time()
            with meter.phase("data"):
                got = evidence.masks(evidence.histogram(sample[1], evidence.differs(attrs)))
                fresh = sorted(set(got) - seen, key=lambda e: (e.bit_count(), e))
                seen.update(fresh)
                gone = 0
                for e in fresh:
                    gone += tree.refute(e)
                    meter.check("data")
            compared = sum(got.values())
            spent = time.time() - at
            meter.step("data", rounds.rounds, len(fresh), gone, compared)
            if plan == "rescan":
                first = next((n for s in range(m + 1) if (n := len(tree.level(s)))), 0)
                going = rounds.learned(sample[0], gone, compared, schema_cost(n, m, k, first, memory == "resident" and rounds.rounds > 1, alpha, beta))
            else:
                going = rounds.learned(sample[0], gone, compared)

    if data_phase and n > 1:
        data_rounds()
    if memory != "resident":
        with meter.phase("schema"):
            count, _ = lattice.counter_for(df, attrs, "rescan", memory, k, meter=meter)
    known = {0: min(1, n)}
    total = n
    level = 0
    while level <= (m if max_lhs is None else max_lhs):
        at = time.time()
        todo = tree.level(level)
        if max_candidates is not None and len(todo) > max_candidates:
            raise MemoryError(f"{len(todo)} candidates of one level, more than {max_candidates}")
        need = set()
        for x, a in todo:
            need.add(x)
            if kind == "fd" and not (prune_keys and known.get(x) == total):
                need.add(x | a)
        with meter.phase("schema"):
            known |= count(sorted(need - set(known)))
            failed = [(x, a) for x, a in todo if (known[x] != known.get(x | a, known[x]) if kind == "fd" else known[x] != total)]
            for x, a in failed:
                tree.specialise(x, a)
        meter.step("schema", level, len(todo), len(failed))
        level += 1
        budget = level_budget if level_budget is not None else 5 * spent
        if data_phase and n > 1 and failed and time.time() - at > budget > 0 and level < m:
            data_rounds()
    return [(x, a if kind == "fd" else 0) for x, a in tree.items()]
