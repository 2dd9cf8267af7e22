"""Level-wise search: the driver keeps counts and candidates, Spark counts the classes of each level's attribute sets."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from depmine.functions.bits import members, subset
from depmine.operators import distribute, partition
from depmine.operators.refine import by_counts
from depmine.sources.io import drop_path, stored

from .result import Meter

Counter = Callable[[list[int]], dict[int, int]]
#: Levels of more sets are joined by Spark in the rescan plans too; the reuse plans join any level of more sets than workers there.
JOIN_ABOVE = 50_000
#: The resident and dealt rescan plans inspect a relation of more rows only where agreements of rows seen before leave anything open.
INSPECT_ROWS = 50_000


def next_level(level: list[int]) -> list[int]:
    """Unions of two sets that differ in their highest attribute, all of whose direct subsets survived."""
    alive, by_prefix = set(level), {}
    for x in level:
        top = 1 << x.bit_length() - 1
        by_prefix.setdefault(x ^ top, []).append(top)
    out = []
    for prefix, tops in by_prefix.items():
        for i, a in enumerate(sorted(tops)):
            for b in sorted(tops)[i + 1 :]:
                x = prefix | a | b
                if all(x ^ 1 << c in alive for c in members(x)):
                    out.append(x)
    return out


def next_level_df(level: DataFrame) -> DataFrame:
    """The same for levels too large for the driver: a self-join on the prefix, then a check of the subsets. level: (mask)."""
    top = lambda c: F.expr(f"shiftleft(1L, length(bin({c})) - 1)")
    keyed = level.select("mask", (F.col("mask").bitwiseXOR(top("mask"))).alias("prefix"))
    pairs = keyed.alias("a").join(keyed.alias("b"), (F.col("a.prefix") == F.col("b.prefix")) & (F.col("a.mask") < F.col("b.mask")))
    made = pairs.select(F.col("a.mask").bitwiseOR(F.col("b.mask")).alias("mask")).distinct()
    bits = F.filter(F.transform(F.sequence(F.lit(0), F.lit(62)), lambda i: F.call_function("shiftleft", F.lit(1).cast("long"), i)), lambda b: F.col("mask").bitwiseAND(b) != 0)
    parts = made.withColumn("bit", F.explode(bits)).select("mask", F.col("mask").bitwiseXOR(F.col("bit")).alias("part"))
    kept = parts.join(level.select(F.col("mask").alias("part")), "part", "left_semi").groupBy("mask").agg(F.count("*").alias("n"))
    return kept.where(F.col("n") == F.bit_count("mask")).select("mask")


def joined(spark: SparkSession, level: list[int], k: int, memory: str) -> list[int]:
    """The next level by a distributed self-join of the level's sets: triangle cells (`resident`) or cartesian with mirrors filtered, on what is left of a set without its highest attribute. Masks travel as text."""
    if not level:
        return []
    top = [x.bit_length() - 1 for x in level]
    rows = spark.createDataFrame([(n, str(x ^ 1 << t), t) for n, (x, t) in enumerate(zip(level, top))], "node int, prefix string, top int")
    pairs = distribute.triangle(rows, k, ["node"], on=["prefix"]) if memory == "resident" else distribute.cartesian(rows, ["node"], on=["prefix"])
    alive = set(level)
    made = {int(r["prefix"]) | 1 << r["a"] | 1 << r["b"] for r in pairs.select(F.col("l_prefix").alias("prefix"), F.col("l_top").alias("a"), F.col("r_top").alias("b")).collect()}  # candidates of a level, which the driver holds anyway
    return sorted(x for x in made if all(x ^ 1 << c in alive for c in members(x)))


class Refuted:
    """Answers what sets determine, from agreements of rows seen before wherever these refute it, else by inspecting all rows.

    An agreement is all that two rows share: they are equal on each set within
    it and refute that such a set is a key or determines anything outside. Sets that
    no agreement refutes are inspected in rounds, of which each adds agreements; nothing is taken to hold without all rows.
    """

    def __init__(self, held):
        self.held, self.seen, self.inspections = held, np.empty(0, np.int64), 0

    def open(self, asked: dict[int, int], seen: np.ndarray) -> dict[int, int]:
        """What of the asked bits these agreements leave open, of sets where they leave any."""

        out = {}
        for x, bits in asked.items():
            over = seen[(seen & x) == x]
            if left := bits & int(np.bitwise_and.reduce(over)) if len(over) else bits:
                out[x] = left
        return out

    def settle(self, asked: dict[int, int]) -> dict[int, int]:
        """Which of the asked bits hold for each set: bit a, that it determines attribute a; bit m, that it is a key."""
        if hasattr(self.held, "sampled"):
            asked, out = self._rounds(self.held.sampled().inspect, asked), dict.fromkeys(asked, 0)
            left = self.open(asked, self.seen)
            return out | self._rounds(self.held.inspect, left, max(512, len(left) // 4))
        return self._rounds(self.held.inspect, asked)

    def _rounds(self, inspect, asked: dict[int, int], size: int = 256) -> dict[int, int]:
        out, left = dict.fromkeys(asked, 0), self.open(asked, self.seen)
        while left:
            step = max(1, len(left) // size)
            turn = {x: left[x] for x in list(left)[::step][:size]}
            held, fresh = inspect(turn)
            out |= held
            self.inspections += len(turn)
            size *= 2
            fresh = np.setdiff1d(fresh, self.seen)
            self.seen = np.concatenate([self.seen, fresh])
            left = self.open({x: bits for x, bits in left.items() if x not in turn}, fresh)
        return out


def run_fd(counts: Counter, m: int, rows: int, max_lhs: int | None, meter: Meter, join: Callable[[list[int]], list[int]] = next_level, max_nodes: int | None = None, held=None) -> list[tuple[int, int]]:
    """Minimal functional dependencies. Each node carries the right sides that are still open for it.

    A node whose attribute set is a key yields its dependencies and goes: whatever lies above it is not minimal.
    max_nodes: refuse a level of more sets. held: inspected instead of counts where it is given, see Refuted.
    """
    everything = (1 << m) - 1
    found: list[tuple[int, int]] = []
    least: dict[int, list[int]] = {}
    size, open_rhs = {0: min(1, rows)}, {0: everything}
    level = [1 << i for i in range(m)]
    depth = 1
    refuted = Refuted(held) if held else None

    def report(lhs: int, rhs: int) -> None:
        found.append((lhs, rhs))
        least.setdefault(rhs, []).append(lhs)

    while level and depth <= (m if max_lhs is None else max_lhs + 1):
        guard(level, max_nodes)
        open_at = {x: reduce(lambda rest, a: rest & open_rhs[x ^ 1 << a], members(x), everything) for x in level}
        with meter.phase("schema"):
            if refuted:
                asked = dict.fromkeys(level, 1 << m)
                for x in level:
                    for a in members(x & open_at[x]):
                        asked[x ^ 1 << a] = asked.get(x ^ 1 << a, 0) | 1 << a
                found_of = refuted.settle(asked)
                holds, unique = lambda lhs, bit: found_of[lhs] & bit, lambda x: found_of[x] >> m & 1
            else:
                size = {x: n for x, n in size.items() if x.bit_count() == depth - 1} | counts(level)
                holds, unique = lambda lhs, bit: by_counts(size[lhs], size[lhs | bit]), lambda x: size[x] == rows
        keep = {}
        for x in level:
            rest = open_at[x]
            for a in members(x & rest):
                bit = 1 << a
                if holds(x ^ bit, bit):
                    report(x ^ bit, bit)
                    rest &= x & ~bit
            keep[x] = rest
        alive = []
        for x in level:
            if unique(x) and (max_lhs is None or depth <= max_lhs):
                for a in members(everything & ~x):
                    bit = 1 << a
                    if not any(subset(y, x) for y in least.get(bit, ())):
                        report(x, bit)
            if keep[x] and not unique(x):
                alive.append(x)
        open_rhs = {x: keep[x] for x in alive}
        meter.step("schema", depth, len(level), len(found))
        with meter.phase("rest"):
            level = join(alive)
        depth += 1
    return found


def guard(level: list[int], max_nodes: int | None) -> None:
    if max_nodes is not None and len(level) > max_nodes:
        raise MemoryError(f"a level of {len(level)} attribute sets, more than {max_nodes}")


def run_ucc(counts: Counter, m: int, rows: int, max_lhs: int | None, meter: Meter, join: Callable[[list[int]], list[int]] = next_level, max_nodes: int | None = None) -> list[tuple[int, int]]:
    """Minimal unique combinations: a set is unique if it has as many classes as there are rows; its supersets go."""
    found, level, depth = [], [1 << i for i in range(m)], 1
    if rows <= 1:
        return [(0, 0)]
    while level and depth <= (m if max_lhs is None else max_lhs):
        guard(level, max_nodes)
        with meter.phase("schema"):
            size = counts(level)
        found += [(x, 0) for x in level if size[x] == rows]
        meter.step("schema", depth, len(level), len(found))
        with meter.phase("rest"):
            level = join([x for x in level if size[x] != rows])
        depth += 1
    return found


class StoredClasses:
    """The reuse plans: the classes of each level lie in shared storage, a folder for each set, and the next level's are made from two parents each.

    memory: `resident` gives pairs of sets to the triangle's cells; `spill`
    joins the sets by cartesian product and their classes by sorted merge;
    `chunked` also reads the parents in pieces of `chunk` sets, so that one
    piece's classes bound what a pass holds. `keep` levels stay, older ones are deleted.
    """

    def __init__(self, df: DataFrame, attrs: list[str], memory: str = "resident", k: int = 8, chunk: int = 8, meter: Meter | None = None, keep: int = 1):
        self.spark, self.memory, self.chunk, self.k, self.meter, self.keep = df.sparkSession, memory, chunk, k, meter, keep
        rows, self.path = stored(df.select(*attrs, F.monotonically_increasing_id().alias("_row")), "rows")
        self.rows, self.attrs, self.n = rows, attrs, rows.count()
        self.nodes = {1 << i: i for i in range(len(attrs))}
        self.store, paths = self._kept(partition.column_classes(rows, attrs, "_row", self.n), len(attrs))
        self.levels = [(self.nodes, self.store, paths)]
        self.sizes = self._sizes()
        deal = distribute.columns_deal(attrs, k)
        if meter:
            meter.loaded("level 1", {w: self.n * list(deal.values()).count(w) for w in set(deal.values())}, {})

    def _kept(self, classes: DataFrame, nodes: int) -> tuple[DataFrame, list[str]]:
        """Classes in folders by set, in files of a bounded number of rows."""
        parts = max(1, -(-self.n // 4_000_000))
        tasks = min(nodes * parts, 8 + self.n * nodes // 1_000_000, 10_000)
        dealt = classes.repartition(max(1, tasks), "node", F.pmod(F.xxhash64("row_id"), F.lit(parts)))
        df, path = stored(dealt, "classes", ["node"])
        return df, [path]

    def _sizes(self) -> dict[int, tuple[int, int]]:
        """(classes, rows of the largest) of each set of the level."""
        classes = self.store.groupBy("node", "class_id").agg(F.count("*").alias("size"))
        rows = classes.groupBy("node").agg(F.count("*").alias("n"), F.max("size").alias("most")).collect()  # a row for each set
        seen = {r["node"]: (r["n"], r["most"]) for r in rows}
        return {x: seen.get(n, (0, 0)) for x, n in self.nodes.items()}

    def join(self, level: list[int]) -> list[int]:
        return joined(self.spark, level, self.k, self.memory) if len(level) > self.k else next_level(level)

    def counts(self, masks: list[int]) -> dict[int, int]:
        fresh = [x for x in masks if x not in self.nodes]
        if fresh:
            self._next(fresh)
        return {x: self.sizes[x][0] for x in masks}

    def _next(self, masks: list[int]) -> None:
        made = {}
        for n, x in enumerate(masks):
            rest = x ^ 1 << x.bit_length() - 1
            made[x] = (n, self.nodes[rest], self.nodes[x ^ 1 << rest.bit_length() - 1])
        if self.meter:
            side = distribute.triangle_side(self.k)
            held: dict[int, set[int]] = {}
            for _, left, right in made.values():
                held.setdefault(min(left % side, right % side) * side + max(left % side, right % side), set()).update((left, right))
            work: dict[int, int] = {}
            for _, left, right in made.values():
                cell = min(left % side, right % side) * side + max(left % side, right % side)
                work[cell] = work.get(cell, 0) + 2 * self.n
            self.meter.loaded(f"level {masks[0].bit_count()}", {c: self.n * len(s) for c, s in held.items()}, work)
        size = self.chunk if self.memory == "chunked" else len(masks)
        parts, paths = [], []
        for at in range(0, len(masks), size):
            part = [made[x] for x in masks[at : at + size]]
            wanted = sorted({p for _, a, b in part for p in (a, b)})
            parents = self.spark.createDataFrame(part, "node int, left int, right int")
            store = self.store.where(F.col("node").isin(wanted))  # reads their folders only
            classes = partition.intersect(store, parents, self.n * len(part), None if self.memory == "resident" else "merge")
            df, path = self._kept(classes, len(part))
            parts.append(df)
            paths += path
        self.store = parts[0]
        for p in parts[1:]:
            self.store = self.store.unionByName(p)
        self.nodes = {x: n for x, (n, _, _) in made.items()}
        self.levels.append((self.nodes, self.store, paths))
        self.sizes = self._sizes()
        for _, _, old in self.levels[: -self.keep]:
            for path in old:
                drop_path(self.spark, path)
        self.levels = self.levels[-self.keep :]

    def with_classes(self, mask: int) -> DataFrame | None:
        """The rows with the class of one stored set: what an ordering check inspects."""
        for nodes, store, _ in self.levels:
            if mask in nodes:
                classes = store.where(F.col("node") == nodes[mask]).select(F.col("row_id").alias("_id"), "class_id")
                return self.rows.join(classes, F.col("_row") == F.col("_id")).drop("_id")
        return None


#: Up to so many rows a set's classes are one value, of which a cell of the resident reuse plan holds a few.
ONE_VALUE = 2_000_000


class StoredCodes(StoredClasses):
    """The resident reuse plan of a relation of 1 to ONE_VALUE rows: the classes of a set are one row of the store, the places and class numbers of the rows that are not alone in their class.

    Sets of one prefix meet in cells of two blocks of parents; a parent is sent to the cells that need it, and no row is joined.
    """

    BLOCK = 4

    def __init__(self, df: DataFrame, attrs: list[str], k: int, meter: Meter | None = None):
        self.spark, self.memory, self.k, self.meter, self.attrs = df.sparkSession, "resident", k, meter, attrs
        rows, self.path = stored(df.select(*attrs, F.monotonically_increasing_id().alias("_row")), "rows")
        self.n = rows.count()

        def column(node):
            def run(batches):
                whole = pa.Table.from_batches(batches)
                codes = partition.encode(whole.select(["v"]))[0][0]
                codes = codes[np.argsort(whole.column("_row").to_numpy())]
                yield shared_rows(node, len(codes), np.arange(len(codes), dtype=np.int32), codes.astype(np.int64))

            return run

        each = [rows.select("_row", F.col(a).alias("v")).coalesce(1).mapInArrow(column(i), CLASSES) for i, a in enumerate(attrs)]  # a task reads one column
        self.nodes = {1 << i: i for i in range(len(attrs))}
        self._keep(reduce(DataFrame.unionByName, each))
        deal = distribute.columns_deal(attrs, k)
        if meter:
            meter.loaded("level 1", {w: self.n * list(deal.values()).count(w) for w in set(deal.values())}, {})

    def _keep(self, classes: DataFrame) -> None:
        self.store, path = stored(classes, "classes")
        seen = {r["node"]: r["n"] for r in self.store.select("node", "n").collect()}  # a row for each set
        self.sizes = {x: (seen[n], 0) for x, n in self.nodes.items()}
        self.kept = path

    def _next(self, masks: list[int]) -> None:
        n, block, places = self.n, self.BLOCK, {}
        cells: dict[tuple[int, int, int], list[tuple[int, int, int]]] = {}
        for node, x in enumerate(masks):
            b = 1 << x.bit_length() - 1
            a = 1 << (x ^ b).bit_length() - 1
            own = places.setdefault(x ^ a ^ b, {})
            at = [own.setdefault(y, len(own)) // block for y in (a, b)]
            cells.setdefault((x ^ a ^ b, *at), []).append((node, self.nodes[x ^ b], self.nodes[x ^ a]))
        work = list(cells.values())
        wanted = [(cell, p) for cell, own in enumerate(work) for p in {p for _, left, right in own for p in (left, right)}]
        if self.meter:
            held = {cell: 0 for cell in range(len(work))}
            for cell, _ in wanted:
                held[cell] += n
            self.meter.loaded(f"level {masks[0].bit_count()}", held, {cell: 2 * n * len(own) for cell, own in enumerate(work)})
        told = self.spark.sparkContext.broadcast(work)

        def run(table):
            parents = {node: (np.frombuffer(at, np.int32), np.frombuffer(numbers, np.int32)) for node, at, numbers in zip(*(table.column(c).to_pylist() for c in ("node", "at", "numbers")))}
            made = []
            for node, left, right in told.value[table.column("cell")[0].as_py()]:
                (at, x), (other, y) = parents[left], parents[right]
                met = np.full(n, -1, np.int32)
                met[other] = y
                both = met[at]
                fit = both >= 0
                made.append(shared_rows(node, n, at[fit], x[fit].astype(np.int64) * (int(y.max(initial=0)) + 1) + both[fit]))
            return pa.Table.from_batches(made)

        dealt = self.store.drop("n").join(F.broadcast(self.spark.createDataFrame(wanted, "cell int, parent int")), F.col("node") == F.col("parent")).drop("parent")
        made = dealt.repartition(min(len(work), 2_000), "cell").groupBy("cell").applyInArrow(run, CLASSES)
        old, self.nodes = self.kept, {x: node for node, x in enumerate(masks)}
        self._keep(made)
        drop_path(self.spark, old)


CLASSES = "node int, n long, at binary, numbers binary"


def shared_rows(node: int, n: int, at: np.ndarray, key: np.ndarray) -> pa.RecordBatch:
    """A row of CLASSES: of n rows, those at these places have these class keys and all others are alone."""
    if len(key) and int(key.max()) <= 4 * len(key):
        number, counts = key, np.bincount(key)
    else:
        _, number, counts = np.unique(key, return_inverse=True, return_counts=True)
    many = counts > 1
    fit = many[number]
    numbers = (np.cumsum(many) - 1).astype(np.int32)[number[fit]] if len(key) else np.empty(0, np.int32)
    cells = ([node], [int((counts > 0).sum()) + n - len(at)], [at[fit].astype(np.int32).tobytes()], [numbers.tobytes()])
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cells, (pa.int32(), pa.int64(), pa.binary(), pa.binary()))], ["node", "n", "at", "numbers"])


def inspectable(counts: Counter, m: int, rows: int):
    """What counts a large relation, if it can inspect single sets, or None."""
    held = getattr(counts, "__self__", None)
    return held if rows > INSPECT_ROWS and m < 62 and hasattr(held, "inspect") else None


def counter_for(df: DataFrame, attrs: list[str], plan: str, memory: str, k: int, strategy: str = "grouping_sets", meter: Meter | None = None) -> tuple[Counter, Callable[[list[int]], list[int]]]:
    """How a plan counts classes and how it joins a level's sets."""
    if plan == "reuse":
        whole = memory == "resident" and partition.dealable(df, attrs) and 0 < df.count() <= ONE_VALUE
        held = StoredCodes(df, attrs, k, meter) if whole else StoredClasses(df, attrs, memory, k, meter=meter)
        return held.counts, held.join
    spark = df.sparkSession
    join = lambda level: joined(spark, level, k, memory) if len(level) > JOIN_ABOVE else next_level(level)
    if memory == "resident":
        held = partition.BroadcastCodes(df, attrs, k)
        if meter:
            meter.told(held.bytes)
        return held.counts, join
    if strategy == "grouping_sets" and partition.dealable(df, attrs) and df.count() > partition.DEALT_ROWS:
        return partition.DealtCodes(df, attrs, k).counts, join
    by = {"grouping_sets": partition.counts_by_grouping_sets, "one_by_one": partition.counts_one_by_one, "fingerprint": partition.counts_by_fingerprint}[strategy]
    return lambda masks: by(df, attrs, masks), join
