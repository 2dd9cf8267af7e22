"""Bounds on the data a worker receives (x) and the work it does (y), as functions of rows n, attributes m, workers k."""

from __future__ import annotations

from math import sqrt

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def bound(method: str, plan: str, memory: str, n: float, m: float, k: float, work: float | None = None, largest: float | None = None, groups: float | None = None, levels: float = 1) -> tuple[float, float]:
    """work: comparisons within classes; largest: the largest class; groups of the sampling rounds (k by default)."""
    work = n * n / 2 if work is None else work
    g = groups or (k if memory == "resident" else 2 * k)
    table = {
        ("lattice", "reuse", "resident"): (2**m * n * sqrt(2 / k), 2**m * 2 * n / k),
        ("lattice", "reuse", "spill"): (2**m * n, 2**m * 2 * n),
        ("lattice", "rescan", "resident"): (n * m, n * m * 2**m / k),
        ("lattice", "rescan", "spill"): (2**m * n * m / k, n * m * 2**m / k),
        ("pair", "reuse", "resident"): (5 * m * m * max(n / k, sqrt(2 * work / k)), 5 * m * work / k),
        ("pair", "reuse", "spill"): (n * m * m, 5 * m * work / k),
        ("pair", "rescan", "resident"): (n * m * sqrt(2 / k), m * n * n / (2 * k)),
        ("pair", "rescan", "spill"): (n * m * 2 / sqrt(k), m * n * n / (2 * k)),
        ("hybrid", "reuse", "resident"): (n * m * (largest or n) / k, n * m * (largest or n) / k),
        ("hybrid", "reuse", "spill"): (n * m * (largest or n), n * m * (largest or n) / k),
        ("hybrid", "rescan", "resident"): (2 * n * m / g, m * (n / g) ** 2),
        ("hybrid", "rescan", "spill"): (2 * n * m / g, m * (n / g) ** 2),
    }
    return table[(method, plan, memory)]


def footprint(method: str, n: float, m: float, k: float) -> float:
    """Values that one worker holds at once."""
    return {"lattice": n * 2**m / sqrt(k), "pair": n * m / sqrt(k), "hybrid": 2 * n * m / k}[method]


def level_join(candidates: int, k: int) -> tuple[float, float]:
    return candidates * sqrt(2 / k), candidates * (candidates - 1) / (2 * k)


def weigh(method: str, plan: str, n, m, k, work=None, alpha: float = 1.0, beta: float = 1.0) -> float:
    """A scalar for choosing: the lattice visits a share of its sets that shrinks with width, a hybrid a few rounds and the low levels."""
    visited = min(2**m, m**3)
    if method == "lattice":
        return alpha * (n * m if plan == "rescan" else visited * n * sqrt(2 / k)) + beta * visited * n * m / k
    x, y = bound(method, plan, "resident", n, m, k, work)
    if method == "hybrid":
        return alpha * (x * 3 + n * m) + beta * (3 * y + m * m * n * m / k)
    return alpha * x + beta * y


def work_in_classes(df: DataFrame, attrs: list[str]) -> DataFrame:
    """(attr, w): comparisons within the classes of each attribute, each pair counted once."""
    parts = None
    for a in attrs:
        own = df.groupBy(a).agg(F.count("*").alias("b")).agg(F.coalesce(F.sum(F.expr("b * (b - 1) div 2")), F.lit(0)).cast("long").alias("w")).select(F.lit(a).alias("attr"), "w")
        parts = own if parts is None else parts.unionByName(own)
    return parts


def maxima(load: DataFrame) -> DataFrame:
    return load.agg(F.max("x").cast("long").alias("meter_x"), F.max("y").cast("long").alias("meter_y"), F.sum("x").cast("long").alias("total_x"), F.sum("y").cast("long").alias("total_y"))


def speed_up(work: dict[int, float]) -> list[tuple[int, float, float]]:
    """(workers, measured, ideal) against the smallest number of workers; work: seconds, or what the busiest worker does."""
    k0 = min(work)
    return [(k, work[k0] / max(t, 1e-9), k / k0) for k, t in sorted(work.items())]


def quadratic(points: list[tuple[float, float]], at: float) -> tuple[float, float, float]:
    """(constant, factor, value at `at`) of the least-squares fit of y = constant + factor * x^2."""
    n = len(points)
    squares = [x * x for x, _ in points]
    mean_s, mean_y = sum(squares) / n, sum(y for _, y in points) / n
    spread = sum((s - mean_s) ** 2 for s in squares)
    factor = sum((s - mean_s) * (y - mean_y) for s, (_, y) in zip(squares, points)) / spread if spread else 0.0
    constant = mean_y - factor * mean_s
    return constant, factor, constant + factor * at * at
