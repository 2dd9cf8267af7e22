"""One entry for all methods, and the choice of plan and memory by estimated cost."""

from __future__ import annotations

from pyspark.sql import DataFrame

from depmine.functions.prep import distinct_nulls
from depmine.sources.io import materialize

from . import cost, dc, hybrid, lattice, od, pairs
from .result import Discovery, LimitExceeded, Meter


def discover(df: DataFrame, kind: str = "fd", method: str = "lattice", plan: str = "rescan", memory: str = "spill", k: int = 8, max_lhs: int | None = None, attrs: list[str] | None = None, null_mode: str = "equal", seed: int = 42, limit_s: float | None = None, **options) -> Discovery:
    """kind fd or ucc; method lattice, pair or hybrid; plan reuse or rescan; memory resident or spill (and chunked for the reuse lattice). A plan beyond a limit ends with the status of that limit and no dependencies."""
    attrs = attrs or df.columns
    df = df.select(*attrs)
    if null_mode == "distinct":
        df = materialize(distinct_nulls(df, attrs), "nulls")
    meter = Meter(limit_s, df.sparkSession, k)
    status, found = "done", []
    try:
        if method == "lattice":
            with meter.phase("rest"):
                counts, join = lattice.counter_for(df, attrs, plan, memory, k, options.pop("strategy", "grouping_sets"), meter)
                rows = df.count()
            if kind == "fd":
                found = lattice.run_fd(counts, len(attrs), rows, max_lhs, meter, join, held=lattice.inspectable(counts, len(attrs), rows), **options)
            else:
                found = lattice.run_ucc(counts, len(attrs), rows, max_lhs, meter, join, **options)
        elif method == "pair":
            found = pairs.run(df, attrs, kind, plan, memory, k, max_lhs, meter, **options)
        elif method == "hybrid":
            found = hybrid.run(df, attrs, kind, plan, memory, k, max_lhs, meter, seed=seed, **options)
        else:
            raise ValueError(f"unknown method {method}")
    except LimitExceeded:
        status = "time limit"
    except MemoryError:
        status = "memory limit"
    return Discovery(df.sparkSession, attrs, kind, found, meter, status)


def whole(df: DataFrame, kind: str = "fd", method: str = "lattice", plan: str = "rescan", memory: str = "spill", **options) -> Discovery:
    """discover(); where its plan refuses for memory, the plan that spills gives the same whole result: lattice for lattice, hybrid for pairs and hybrid."""
    done = discover(df, kind, method, plan, memory, **options)
    if done.status != "memory limit":
        return done
    kept = {o: options[o] for o in ("k", "max_lhs", "attrs", "null_mode", "seed", "limit_s") if o in options}
    return discover(df, kind, "lattice" if method == "lattice" else "hybrid", "rescan", "spill", **kept)


def order_dependencies(df: DataFrame, attrs: list[str], plan: str = "rescan", memory: str = "spill", k: int = 8, lists: bool = True, max_context: int | None = None, directions=("asc", "desc"), meter: Meter | None = None) -> DataFrame:
    """Unary list dependencies, or with lists=False the minimal set-based ones in contexts of any size, or of at most max_context attributes. A plan that refuses gives way to the one that spills."""
    df = df.select(*attrs)
    meter = meter or Meter(spark=df.sparkSession, workers=k)
    try:
        check = od.checker(df, attrs, plan, memory, k, meter)
    except MemoryError:
        check = od.checker(df, attrs, "rescan", "spill", k, meter)
    found = od.unary(attrs, meter, check, directions) if lists else od.run(attrs, df.count(), meter, check, max_context, directions)
    return df.sparkSession.createDataFrame(found, od.OD)


def denial_constraints(df: DataFrame, attrs: list[str], method: str = "pair", plan: str = "rescan", memory: str = "resident", k: int = 8, max_predicates: int = 5, meter: Meter | None = None, **options) -> DataFrame:
    """Minimal constraints of at most max_predicates predicates: (dc, n_predicates). cross and single widen the predicate space."""
    run = dc.run_pairs if method == "pair" else dc.run_hybrid
    found = run(df.select(*attrs), attrs, plan, memory, k, max_predicates, meter or Meter(spark=df.sparkSession, workers=k), **options)
    return df.sparkSession.createDataFrame([(q, q.count(" and ") + 1) for q in found], "dc string, n_predicates int")


def share_bytes(method: str, n: int, m: int, k: int, code_bytes: int = 4) -> float:
    """What one worker of a resident rescan plan holds: all codes, two sides of a triangle cell, or two groups."""
    return {"lattice": n * m, "pair": n * m * (2 / k) ** 0.5, "hybrid": 2 * n * m / k}[method] * code_bytes


def choose(n: int, m: int, k: int, worker_bytes: int, code_bytes: int = 4, work_in_classes: int | None = None) -> tuple[str, str, str]:
    """(method, plan, memory) of least estimated time. Pairs pay where columns are many and rows few, the lattice where rows are many; plans that outgrow a worker spill."""
    best = min((cost.weigh(method, plan, n, m, k, work_in_classes), method, plan) for method in ("lattice", "pair", "hybrid") for plan in ("reuse", "rescan"))
    return best[1], best[2], "resident" if share_bytes(best[1], n, m, k, code_bytes) <= worker_bytes else "spill"
