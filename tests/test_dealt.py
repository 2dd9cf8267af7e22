"""Class counts of relations too large for one broadcast or one wide exchange."""

from itertools import combinations

import duckdb
import pytest
from pyspark.sql import functions as F

from depmine.operators import partition
from depmine.plans import lattice, planner
from depmine.plans.result import Meter
from depmine.queries import ATTRS, ODD, QUERIES, SQL, odd_values


@pytest.fixture
def few(monkeypatch):
    monkeypatch.setattr(partition, "DEALT_ROWS", 100)
    monkeypatch.setattr(partition, "PART_ROWS", 150)


def oracle(tiny, table, name):
    con = duckdb.connect()
    con.execute(f"create view {table} as select * from '{tiny}/{table}.parquet'")
    return {tuple(r) for r in con.execute(SQL[name]).fetchall()}


def rows(df):
    return {tuple(r) for r in df.collect()}


@pytest.mark.parametrize("most", [2_000_000, 400])
def test_dealt_codes_count_like_groupings(spark, tiny, few, monkeypatch, most):
    """Also odd values, and attributes with a value too frequent for a task."""
    monkeypatch.setattr(partition, "MOST_ROWS", most)
    df = odd_values(spark, tiny).withColumn("hot", F.when(F.col("a") < 20, F.monotonically_increasing_id() % 301)).withColumn("d", F.expr("cast(a as decimal(9,2))"))
    attrs = [*ODD, "hot", "d"]
    masks = [sum(1 << i for i in c) for s in (0, 1, 2, 7) for c in combinations(range(7), s)]
    held = partition.DealtCodes(df, attrs, 2)
    assert held.counts(masks) == partition.counts_by_grouping_sets(df, attrs, masks)
    assert held.kept and (most > 400) == (5 in held.dealers)


def test_level_counts_end_where_no_broadcast_fits(spark, tiny, few, monkeypatch):
    def refuse(*a, **o):
        raise MemoryError

    monkeypatch.setattr(partition, "BroadcastCodes", refuse)
    name = "class_counts_lineitem_level2_broadcast"
    assert rows(QUERIES[name](spark, tiny)) == oracle(tiny, "lineitem", name)


def test_fingerprints_are_exchanged_a_bounded_number_at_once(spark, tiny, monkeypatch):
    made, select = [], partition.F.array
    monkeypatch.setattr(partition, "EXCHANGE_ROWS", 20_000)
    monkeypatch.setattr(partition.F, "array", lambda *c: made.append(len(c)) or select(*c))
    name = "class_counts_lineitem_level2_by_fingerprint"
    assert rows(QUERIES[name](spark, tiny)) == oracle(tiny, "lineitem", name)
    n = spark.read.parquet(f"{tiny}/lineitem.parquet").count()
    assert sum(made) == 55 and max(made) * n <= 20_000


@pytest.mark.parametrize("name", ["fd_orders_lattice_rescan_spill", "fd_orders_hybrid_rescan_spill"])
def test_large_relations_are_dealt_by_few_attributes(spark, tiny, few, monkeypatch, name):
    """All levels read parts that one exchange an attribute made; only sets of attributes with few values are grouped."""
    grouped, own = [], partition.counts_by_grouping_sets
    monkeypatch.setattr(partition, "counts_by_grouping_sets", lambda df, attrs, masks: grouped.extend(masks) or own(df, attrs, masks))
    assert rows(QUERIES[name](spark, tiny)) == oracle(tiny, "orders", name)
    assert all(not m & 1 for m in grouped)


def test_hybrid_refuses_before_it_samples(spark, tiny, monkeypatch):
    from depmine.plans import pairs

    def refuse(*a, **o):
        raise MemoryError

    monkeypatch.setattr(partition, "BroadcastCodes", refuse)
    monkeypatch.setattr(pairs, "compacted", lambda *a, **o: pytest.fail("rows were prepared"))
    assert planner.discover(spark.read.parquet(f"{tiny}/orders.parquet").select(*ATTRS["orders"]), method="hybrid", memory="resident").status == "memory limit"


def test_stored_codes_count_like_grouping_sets(spark):
    """The resident reuse plan keeps a set's classes as one value: nulls, NaN, -0.0, repeated rows, a constant; and no rows at all."""
    rows = [(i % 6, None if i % 5 == 0 else float("nan") if i % 5 == 1 else [0.0, -0.0, 1.5][i % 3], None if i % 4 == 0 else "abc"[i % 3], 1, i // 2, i % 7) for i in range(150)]
    df = spark.createDataFrame(rows, "a int, b double, c string, d int, e long, f long").repartition(3)
    held = lattice.StoredCodes(df, df.columns, 4)
    for size in (1, 2, 3):
        masks = [x for x in range(1, 1 << 6) if x.bit_count() == size]
        assert held.counts(masks) == partition.counts_by_grouping_sets(df, df.columns, masks)
    none = df.where("a < 0")
    counts, _ = lattice.counter_for(none, none.columns, "reuse", "resident", 4)
    assert counts([1, 2]) == {1: 0, 2: 0}


@pytest.mark.parametrize("table", ["lineitem", "odd"])
def test_lattice_inspects_only_what_agreements_leave_open(spark, tiny, few, monkeypatch, table):
    """both rescan plans of large relations find what counting each set finds, and look at few sets in all rows."""
    monkeypatch.setattr(partition, "PART_ROWS", 800)
    df, attrs = (odd_values(spark, tiny), ODD) if table == "odd" else (spark.read.parquet(f"{tiny}/lineitem.parquet"), ATTRS["lineitem"][:8])
    df, m, n = df.select(*attrs).cache(), len(attrs), df.count()
    meter = Meter(spark=spark)
    codes = partition.BroadcastCodes(df, attrs, 2)
    expected = sorted(lattice.run_fd(codes.counts, m, n, None, meter))
    sets = sum(size for _, _, size, _, _ in meter.steps)
    for held in (codes, partition.DealtCodes(df, attrs, 2)):
        refuted, init = [], lattice.Refuted.__init__
        monkeypatch.setattr(lattice.Refuted, "__init__", lambda self, held, init=init, refuted=refuted: (init(self, held), refuted.append(self))[0])
        assert sorted(lattice.run_fd(held.counts, m, n, None, Meter(spark=spark), held=held)) == expected
        assert table == "odd" or refuted[0].inspections < sets
    monkeypatch.setattr(lattice, "INSPECT_ROWS", 100)
    assert lattice.inspectable(codes.counts, m, n) is codes and lattice.inspectable(codes.counts, 62, n) is None
