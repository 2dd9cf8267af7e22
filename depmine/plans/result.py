"""What a discovery returns: dependencies, trace and cost as DataFrames."""

from __future__ import annotations

import time
import uuid
from contextlib import contextmanager
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from depmine.functions.bits import names

FD = "lhs string, rhs string, lhs_size int"
UCC = "lhs string, lhs_size int"
COST = "phase string, seconds double, shuffle_mb double, worker_mb double, broadcast_mb double"


class LimitExceeded(RuntimeError):
    """A run over its time or memory limit."""


def _each(sequence):
    at = sequence.iterator()
    while at.hasNext():
        yield at.next()


def shuffled(spark: SparkSession, tag: str, workers: int) -> tuple[int, int]:
    """(bytes, most for one worker) that the jobs of a tag read from shuffles; the tasks of a stage are dealt to workers round robin.

    Read from the driver's own status store: (0, 0) where there is none.
    """
    try:
        scala = spark.sparkContext._jsc.sc()
        scala.listenerBus().waitUntilEmpty()
        store, seen, load, total = scala.statusStore(), set(), [0] * workers, 0
        for j in _each(store.jobsList(None)):
            if not j.jobTags().contains(tag):
                continue
            for stage in map(int, filter(None, j.stageIds().mkString(",").split(","))):
                if stage in seen:
                    continue
                seen.add(stage)
                data = store.lastStageAttempt(stage)
                if data.shuffleReadBytes():
                    total += data.shuffleReadBytes()
                    for t in _each(store.taskList(stage, data.attemptId(), 1_000_000)):
                        if t.taskMetrics().isDefined():
                            read = t.taskMetrics().get().shuffleReadMetrics()
                            load[t.index() % workers] += read.localBytesRead() + read.remoteBytesRead()
        return total, max(load)
    except Exception:  # a figure beside the result, never a reason to fail
        return 0, 0


@dataclass
class Meter:
    """Seconds, shuffled and broadcast bytes by phase, counted loads of workers, and the trace of an iteration."""

    limit_s: float | None = None
    spark: SparkSession | None = None
    workers: int = 8
    seconds: dict[str, float] = field(default_factory=dict)
    tags: dict[str, str] = field(default_factory=dict)
    steps: list[tuple] = field(default_factory=list)
    loads: list[tuple] = field(default_factory=list)
    broadcast: int = 0
    began: float = field(default_factory=time.time)

    @contextmanager
    def phase(self, name: str):
        """Jobs inside belong to the phase. Without a session only seconds are taken."""
        at, context = time.time(), self.spark.sparkContext if self.spark else None
        if context:
            tag = self.tags.setdefault(name, f"depmine-{name}-{uuid.uuid4().hex}")
            context.addJobTag(tag)
        try:
            yield
        finally:
            if context:
                context.removeJobTag(tag)
            self.seconds[name] = self.seconds.get(name, 0.0) + time.time() - at

    def step(self, phase: str, level: int, size: int, found: int, compared: int = 0) -> None:
        self.steps.append((phase, level, size, found, compared))
        self.check(f"{phase} {level}")

    def check(self, at: str) -> None:
        if self.limit_s is not None and time.time() - self.began > self.limit_s:
            raise LimitExceeded(f"over {self.limit_s} s in {at}")

    def told(self, size: int) -> None:
        """Bytes that every worker is sent once."""
        self.broadcast += size

    def loaded(self, step: str, received: dict[int, int], work: dict[int, int]) -> None:
        """Values that each worker received and touched in a step, by the plan's own routing."""
        self.loads += [(step, w, received.get(w, 0), work.get(w, 0)) for w in sorted(received.keys() | work.keys())]

    def costs(self) -> list[tuple]:
        out = []
        for name, s in self.seconds.items():
            total, most = shuffled(self.spark, self.tags[name], self.workers) if name in self.tags else (0, 0)
            out.append((name, s, total / 1e6, most / 1e6, 0.0))
        whole = time.time() - self.began
        out.append(("total", whole, sum(r[2] for r in out), sum(r[3] for r in out), self.broadcast / 1e6))
        return out


@dataclass
class Discovery:
    spark: SparkSession
    attrs: list[str]
    kind: str
    found: list[tuple[int, int]]  # (lhs mask, rhs bit); rhs 0 for unique combinations
    meter: Meter
    status: str = "done"

    def __post_init__(self):
        self.ended = time.time()

    @property
    def seconds(self) -> float:
        return self.ended - self.meter.began

    @property
    def dependencies(self) -> DataFrame:
        if self.status != "done":
            raise LimitExceeded(f"no whole result: {self.status}")
        if self.kind == "ucc":
            return self.spark.createDataFrame([(names(x, self.attrs), x.bit_count()) for x, _ in self.found], UCC)
        return self.spark.createDataFrame([(names(x, self.attrs), names(a, self.attrs), x.bit_count()) for x, a in self.found], FD)

    @property
    def trace(self) -> DataFrame:
        return self.spark.createDataFrame(self.meter.steps, "phase string, level int, size long, found long, compared long")

    @property
    def loads(self) -> DataFrame:
        """(step, worker, x, y): values received and touched, counted from the routing."""
        return self.spark.createDataFrame(self.meter.loads, "step string, worker int, x long, y long")

    @property
    def cost(self) -> DataFrame:
        """A row for each phase and the total: seconds, MB read from shuffles in all and by the worker that read most, MB broadcast to each worker."""
        return self.spark.createDataFrame([(a, *map(float, b)) for a, *b in self.meter.costs()], COST)
