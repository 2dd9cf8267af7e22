"""The published experiments as reports on the given tables: plans, memory, workers, rows, columns, and methods by relation.

Every report has a row for each run: what ran, how many dependencies it found
or which limit it met, its seconds, and the MB it read from shuffles in all
and for the busiest worker. Limits count pairs, sets or dependencies, so that
they are met at the same place on any machine.
"""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from depmine.operators import distribute
from depmine.sources.views import relation

from . import baselines, cost, dc, hybrid, od, pairs, planner
from .result import Meter

REPORT = "experiment string, relation string, n_rows long, n_columns int, method string, plan string, memory string, k int, n_found long, status string, seconds double, data_s double, schema_s double, rest_s double, shuffle_mb double, worker_mb double, broadcast_mb double"
FD_METHODS = (("lattice", "rescan", "resident"), ("pair", "rescan", "resident"), ("hybrid", "rescan", "resident"))
#: What runs on wide relations, and the seven methods of the scaling experiments: kind and method.
FD_KINDS = (("fd", "lattice"), ("fd", "hybrid"), ("ucc", "hybrid"))
SEVEN = (("fd", "lattice"), ("fd", "pair"), ("fd", "hybrid"), ("ucc", "hybrid"), ("od", "lattice"), ("dc", "pair"), ("dc", "hybrid"))
#: Limits of the reports: pairs of rows, sets or candidates of a level, dependencies for the driver.
LIMITS = {"max_pairs": 100_000_000, "max_nodes": 10_000, "max_covers": 30_000, "max_candidates": 20_000}
#: The same without a limit on pairs, for reports that promise whole results at any size.
WHOLE = LIMITS | {"max_pairs": None}
#: Seconds after which a run on a wide relation ends with the time limit.
LIMIT_S = 30.0


def discovered(df: DataFrame, kind: str, method: str, plan: str, memory: str, k: int = 8, limits: dict = LIMITS, **options) -> tuple[int, str, Meter, float]:
    """(number found, status, meter, seconds) of one run of any of the seven methods."""
    attrs, at = df.columns, time.time()
    own = {"lattice": ("max_nodes",), "pair": ("max_pairs", "max_covers"), "hybrid": ("max_candidates",)}[method]
    limit = {x: limits[x] for x in own if x in limits}
    if kind in ("fd", "ucc"):
        done = planner.discover(df, kind, method, plan, memory, k=k, **limit, **options)
        return len(done.found), done.status, done.meter, done.seconds
    meter = Meter(spark=df.sparkSession, workers=k)
    try:
        if kind == "od":
            found = od.run(attrs, df.count(), meter, od.checker(df, attrs, plan, memory, k, meter), **options)
        else:
            run = dc.run_pairs if method == "pair" else dc.run_hybrid
            found = run(df, attrs, plan, memory, k, options.pop("max_predicates", 5), meter, max_pairs=limits.get("max_pairs", 5_000_000_000), **options)
        return len(found), "done", meter, time.time() - at
    except MemoryError:
        return 0, "memory limit", meter, time.time() - at


def report_row(experiment: str, name: str, df: DataFrame, n: int, kind: str, method: str, plan: str, memory: str, k: int = 8, **options) -> tuple:
    found, status, meter, seconds = discovered(df, kind, method, plan, memory, k, **options)
    costs = {r[0]: r for r in meter.costs()}
    phase = lambda p: float(costs[p][1]) if p in costs else 0.0
    total = costs["total"]
    return experiment, name, n, len(df.columns), f"{kind}_{method}", plan, memory, k, found, status, seconds, phase("data"), phase("schema"), phase("rest") + phase("covers"), float(total[2]), float(total[3]), float(total[4])


def reported(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, REPORT)


def plans(spark: SparkSession, sf_dir: str, method: str, relations=("part", "customer", "star14"), memories=("resident",), **options) -> DataFrame:
    """The original plan against the redesigned one on whole relations, by phase and with shuffled MB."""
    rows = []
    for name in relations:
        df = relation(spark, sf_dir, name)
        n = df.count()
        rows += [report_row(f"{method} plans", name, df, n, "fd", method, plan, memory, **options) for plan in ("reuse", "rescan") for memory in memories]
    return reported(spark, rows)


def memories(spark: SparkSession, sf_dir: str, relations=("part", "orders"), worker_mb=(5.0, 0.05), **options) -> DataFrame:
    """The rescan plans with room for the data at each worker, and with less: a worker of worker_mb MB that cannot hold its share takes the plan that spills."""
    rows = []
    for name in relations:
        df = relation(spark, sf_dir, name)
        n = df.count()
        for mb in worker_mb:
            for method in ("lattice", "pair", "hybrid"):
                held = planner.share_bytes(method, n, len(df.columns), 8)
                memory = "resident" if held <= mb * 1e6 else "spill"
                rows.append(report_row(f"workers of {mb:g} MB", name, df, n, "fd", method, "rescan", memory, **options))
    return reported(spark, rows)


def pair_growth(spark: SparkSession, sf_dir: str, name: str = "lineitem", percents=(5, 10, 15, 20)) -> DataFrame:
    """The pair method at four sizes, its quadratic fit, and what the fit says of the whole relation: (memory, percent, n_rows, seconds, fitted)."""
    df, out = relation(spark, sf_dir, name), []
    share = lambda p: df.where(F.pmod(F.xxhash64(*df.columns), F.lit(100)) < p)
    whole = df.count()
    for memory in ("resident", "spill"):
        points = []
        for p in percents:
            part = share(p)
            n = part.count()
            points.append((p, n, discovered(part, "fd", "pair", "rescan", memory)[3]))
        fitted = lambda n: cost.quadratic([(x, s) for _, x, s in points], n)[2]  # noqa: B023, E731
        out += [(memory, p, n, float(s), float(fitted(n))) for p, n, s in points] + [(memory, 100, whole, None, float(fitted(whole)))]
    return spark.createDataFrame(out, "memory string, percent int, n_rows long, seconds double, fitted double")


def workers(spark: SparkSession, sf_dir: str, name: str = "part", ks=(1, 3, 6, 10, 28, 55)) -> DataFrame:
    """What the busiest of k workers receives and does in each of the seven methods (resident rescan plans), counted from the plans' own routing, with speed-up against the ideal: (method, k, x, y, speed_up, ideal, footprint)."""
    df = relation(spark, sf_dir, name)
    attrs, out = df.columns, []
    rows, _, n = pairs.compacted(df, attrs)
    m = len(attrs)
    levels = {}
    for kind, method in SEVEN:
        if method == "lattice":
            _, _, meter, _ = discovered(df, kind, method, "rescan", "resident")
            levels[kind] = [(max(size, asked), n) for _, _, size, _, asked in meter.steps]
    for kind, method in SEVEN:
        loads = {}
        for k in ks:
            if method == "lattice":  # every worker gets one copy; candidates are dealt
                x, y = n * m, sum(-(-size // k) * rows_each for size, rows_each in levels[kind]) * m
            elif method == "pair":
                width = m if kind == "fd" else 3 * m
                load = cost.maxima(distribute.load_of(distribute.triangle(rows, k, pairs.ORDER), distribute.triangle_routes(rows, k, pairs.ORDER), "cell", width)).first()
                x, y = load["meter_x"], load["meter_y"]
            else:
                grouped = distribute.with_groups(rows, max(k, 2), pairs.ORDER)
                own = distribute.PairSchedule(max(k, 2), k).round(0)
                left, right = distribute.group_routes(grouped, own)
                load = cost.maxima(distribute.load_of(distribute.group_pairs(grouped, own, pairs.ORDER), left.unionByName(right), "cell", m)).first()
                x, y = load["meter_x"], load["meter_y"]
                if kind != "dc":  # then the levels, as the lattice has them
                    y += sum(-(-size // k) * rows_each for size, rows_each in levels["fd"]) * m
            loads[k] = (x, y)
        share = {k: y for k, (_, y) in loads.items()}
        held = {"lattice": lambda k: n * m, "pair": lambda k: cost.footprint("pair", n, m, k), "hybrid": lambda k: cost.footprint("hybrid", n, m, k)}[method]
        out += [(f"{kind}_{method}", k, int(loads[k][0]), int(loads[k][1]), float(s), float(i), float(held(k))) for k, s, i in cost.speed_up(share)]
    return spark.createDataFrame(out, "method string, k int, x long, y long, speed_up double, ideal double, footprint double")


def by_rows(spark: SparkSession, sf_dir: str, name: str, percents=(20, 40, 60, 80, 100), methods=SEVEN, **options) -> DataFrame:
    """Deterministic shares of the rows, up to all."""
    df, rows = relation(spark, sf_dir, name), []
    for p in percents:
        part = df.where(F.pmod(F.xxhash64(*df.columns), F.lit(100)) < p) if p < 100 else df
        n = part.count()
        rows += [report_row(f"{p} % of the rows", name, part, n, kind, method, "rescan", "resident", **options) for kind, method in methods]
    return reported(spark, rows)


def by_columns(spark: SparkSession, sf_dir: str, name: str, sizes, n_rows: int | None = None, methods=SEVEN[:4], **options) -> DataFrame:
    """Prefixes of a wide relation's columns, up to all. n_rows: as many rows as the published experiment has."""
    df, rows = relation(spark, sf_dir, name), []
    n = df.count()
    if n_rows and n > n_rows:
        df = df.where(F.pmod(F.xxhash64(*df.columns), F.lit(n)) < n_rows)
        n = df.count()
    for size in sizes:
        part = df.select(df.columns[:size])
        rows += [report_row(f"{size} columns", name, part, n, kind, method, "rescan", "resident", **(options if kind in ("od", "dc") else {"limit_s": LIMIT_S} | options)) for kind, method in methods]
    return reported(spark, rows)


def by_relation(spark: SparkSession, sf_dir: str, names=("star14", "lineitem", "wide24", "wide39", "wide60", "wide109"), methods=FD_METHODS, **options) -> DataFrame:
    """The three methods on six whole relations, with limits."""
    rows = []
    for name in names:
        df = relation(spark, sf_dir, name)
        n = df.count()
        rows += [report_row("methods by relation", name, df, n, "fd", *m, **{"limit_s": LIMIT_S} | options) for m in methods]
    return reported(spark, rows)


def three_versions(spark: SparkSession, sf_dir: str, name: str = "part", **options) -> DataFrame:
    """The pair method in one task, in its original design and in the distribution-friendly one."""
    df = relation(spark, sf_dir, name)
    n, at = df.count(), time.time()
    alone = baselines.single_task(df, "pair").count()
    seconds = time.time() - at
    rows = [("three versions", name, n, len(df.columns), "fd_pair", "single task", "resident", 1, alone, "done", seconds, 0.0, 0.0, 0.0, 0.0, 0.0, 0.0)]
    return reported(spark, rows + [report_row("three versions", name, df, n, "fd", "pair", plan, "resident", **options) for plan in ("reuse", "rescan")])


def phases(spark: SparkSession, sf_dir: str, name: str = "star14") -> DataFrame:
    """Rounds and levels of the hybrid method, of both plans: what a long narrow relation and a wide one spend where."""
    df, out = relation(spark, sf_dir, name), []
    for plan in ("reuse", "rescan"):
        meter = Meter(spark=spark, workers=8)
        hybrid.run(df, df.columns, "fd", plan, "resident", 8, None, meter)
        out += [(plan, *s) for s in meter.steps]
    return spark.createDataFrame(out, "plan string, phase string, level int, size long, found long, compared long")
