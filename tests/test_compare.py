import time

import duckdb
import numpy as np
import pytest

from depmine.operators import compare, distribute, evidence, predicates
from depmine.plans import dc, pairs, planner, workloads
from depmine.queries import QUERIES, SQL


def histogram(df):
    return {r[0]: r[1] for r in df.collect()}


@pytest.fixture(scope="module")
def odd(spark):
    rows = [(i % 7, None if i % 5 == 0 else float("nan") if i % 5 == 1 else [0.0, -0.0, 1.5][i % 3], None if i % 4 == 0 else "abc"[i % 3], i) for i in range(200)]
    return pairs.compacted(spark.createDataFrame(rows, "a int, b double, c string, d long"), list("abcd"))


@pytest.mark.parametrize("plan,memory", [("rescan", "resident"), ("rescan", "spill"), ("reuse", "resident"), ("reuse", "spill")])
def test_blocks_of_pairs_equal_pairs_as_rows(odd, plan, memory, monkeypatch):
    rows, _, n = odd
    monkeypatch.setattr(compare, "SIDE_ROWS", 50)
    monkeypatch.setattr(compare, "BLOCK_ROWS", 40)
    monkeypatch.setattr(compare, "SHORT", 8)
    want = evidence.histogram(pairs.pairs_of(rows, list("abcd"), plan, memory, 8), evidence.differs(list("abcd")))
    assert histogram(pairs.evidence_of(rows, n, list("abcd"), plan, memory, 8)) == histogram(want)


@pytest.mark.parametrize("width", [8, 9, 17])
def test_wide_evidence_is_counted_whole(spark, width):
    attrs = [f"x{i}" for i in range(width)]
    rows, _, n = pairs.compacted(spark.createDataFrame([tuple((r * 7 + c * c) % (c + 2) for c in range(width)) for r in range(60)], ", ".join(f"{a} int" for a in attrs)), attrs)
    want = evidence.histogram(pairs.pairs_of(rows, attrs, "rescan", "resident", 3), evidence.differs(attrs))
    assert histogram(pairs.evidence_of(rows, n, attrs, "rescan", "resident", 3)) == histogram(want)


def test_hundreds_of_millions_of_pairs_are_compared_in_a_minute(spark):
    """Pairs as rows took longer than that for 200 million."""
    df = spark.range(30_000).selectExpr("id", "id % 1000 as a", "id % 7 as b", "cast(id % 13 as string) as c", "id % 50 as d", "id * 37 % 20011 as e")
    rows, _, n = pairs.compacted(df, df.columns)
    at = time.time()
    found = histogram(pairs.evidence_of(rows, n, df.columns, "rescan", "resident", 8))
    assert sum(found.values()) == n * (n - 1) // 2 and time.time() - at < 60


@pytest.mark.parametrize("name", ["dc_part_pair_rescan_resident", "dc_part_pair_rescan_spill", "dc_part_pair_reuse_resident", "dc_part_pair_reuse_spill", "dc_part_covers_in_tasks", "dc_orders_pair_rescan_resident"])
def test_constraints_from_all_pairs_have_no_limit(spark, tiny, name, monkeypatch):
    """A relation said to have more than 5 billion pairs is compared whole."""
    whole = pairs.compacted
    monkeypatch.setattr(pairs, "compacted", lambda *a, **o: (*whole(*a, **o)[:2], 120_000))
    monkeypatch.setattr(compare, "SIDE_ROWS", 60_000)
    monkeypatch.setattr(compare, "BLOCK_ROWS", 60_000)
    con = duckdb.connect()
    t = name.split("_")[1]
    con.execute(f"create view {t} as select * from '{tiny}/{t}.parquet'")
    assert {tuple(r) for r in QUERIES[name](spark, tiny).collect()} == set(con.execute(SQL[name]).fetchall())


@pytest.mark.parametrize("report", [lambda s, d, o: workloads.plans(s, d, "pair", ("part",), **o), lambda s, d, o: workloads.memories(s, d, ("part",), (5.0,), **o), lambda s, d, o: workloads.three_versions(s, d, **o)], ids=["plans_pair_small", "memories_small", "three_versions_part"])
def test_reports_with_sql_end_at_any_size(spark, tiny, report, monkeypatch):
    """More pairs than the reports' limit are no reason to end without a result."""
    monkeypatch.setitem(workloads.LIMITS, "max_pairs", 10)
    assert {r["status"] for r in report(spark, tiny, {"limits": workloads.WHOLE}).collect()} == {"done"}
    assert planner.discover(spark.read.parquet(f"{tiny}/part.parquet"), method="pair", max_pairs=10).status == "memory limit"


def test_slots_of_two_attributes_equal_pairs_as_rows(spark):
    """Whole numbers against doubles with null, NaN and -0.0, across rows and within one, and texts of two attributes."""
    rows = [(i, None if i % 5 == 0 else i % 7, None if i % 6 == 0 else float("nan") if i % 6 == 1 else [0.0, -0.0, 1.5, 3.0][i % 4], "abc"[i % 3], None if i % 4 == 0 else "bcd"[i % 3]) for i in range(120)]
    df = spark.createDataFrame(rows, "a long, b int, c double, d string, e string")
    bare, _, n = pairs.compacted(df, df.columns)
    space = predicates.space_of(df, df.columns, cross=True, single=True, overlap=0.0)
    form = compare.SlotForm(space.slots, len(df.columns))
    assert form.fits(bare) and len(space.slots) == 21
    got = evidence.masks(compare.triangle(bare, n, 6, pairs.ORDER, form))
    expected = evidence.masks(evidence.histogram(distribute.triangle(bare, 6, pairs.ORDER), space.codes()))

    def unordered(seen):
        out = {}
        for c, m in seen.items():
            key = min(c, space.mirrored(c))
            out[key] = out.get(key, 0) + m
        return out

    assert unordered(got) == unordered(expected) and sum(got.values()) == n * (n - 1) // 2


def test_hybrid_of_few_pairs_compares_them_once(spark, monkeypatch):
    """Violations of a wide space come from one comparison of all pairs, not from joins by candidate."""
    df = spark.createDataFrame([(i, i * 7 % 40, float(i % 9)) for i in range(300)], "a int, b int, c double")
    calls = []
    triangle = compare.triangle
    monkeypatch.setattr(compare, "triangle", lambda *a: calls.append(1) or triangle(*a))
    wide = dict(cross=True, single=True, overlap=0.0, max_predicates=3)
    hybrid = planner.denial_constraints(df, df.columns, "hybrid", **wide).collect()
    assert len(calls) == 1
    assert hybrid == planner.denial_constraints(df, df.columns, "pair", **wide).collect() and hybrid


@pytest.mark.parametrize("plan,memory", [("rescan", "resident"), ("rescan", "spill"), ("reuse", "resident"), ("reuse", "spill")])
def test_pairs_counted_by_classes_equal_pairs_as_rows(odd, plan, memory, monkeypatch):
    """Nulls, NaN and -0.0 in cells of one and of two blocks, none of whose pairs is compared."""
    rows, _, n = odd
    monkeypatch.setattr(compare, "CLASS_SIDE", 50)
    monkeypatch.setattr(compare, "CLASS_BLOCK", 40)
    monkeypatch.setattr(compare, "SHORT", 1)
    monkeypatch.setattr(compare, "many", lambda pairs, rows, form: form.by_classes)
    want = evidence.histogram(pairs.pairs_of(rows, list("abcd"), plan, memory, 8), evidence.differs(list("abcd")))
    assert histogram(pairs.evidence_of(rows, n, list("abcd"), plan, memory, 8)) == histogram(want)


@pytest.mark.parametrize("memory", ["resident", "spill"])
def test_tens_of_billions_of_pairs_are_counted_in_a_minute(spark, memory):
    """One by one they took several minutes."""
    df = spark.range(300_000).selectExpr("id", "id % 1000 as a", "id % 7 as b", "cast(id % 13 as string) as c", "id * 37 % 20011 as e")
    rows, _, n = pairs.compacted(df, df.columns)
    at = time.time()
    found = histogram(pairs.evidence_of(rows, n, df.columns, "rescan", memory, 8))
    assert sum(found.values()) == n * (n - 1) // 2 and time.time() - at < 60
    for a, bit in (("a", 2), ("b", 4), ("c", 8), ("e", 16)):
        agreeing = df.groupBy(a).count().selectExpr("sum(count * (count - 1) div 2)").first()[0]
        assert sum(m for e, m in found.items() if not e & bit) == agreeing


def test_distinct_evidence_is_that_of_all_pairs(monkeypatch):
    """Random, unique, constant, rising and almost rising columns, with null or without order, by draws, by all pairs of classes and in boxes."""
    draw = np.random.default_rng(1)
    for trial in range(80):
        for name, values in (("DRAWN", (1, 64)), ("ALL_OF", (0, 200, 5_000)), ("LEAF", (2, 16)), ("TOGETHER", (3, 1_000))):
            monkeypatch.setattr(compare, name, int(draw.choice(values)))
        m, n = int(draw.integers(2, 6)), int(draw.integers(5, 300))
        rising = draw.integers(0, n, n)
        kinds = [draw.integers(0, 3, n), draw.permutation(n), rising, rising // 4, np.maximum(rising + draw.integers(-2, 3, n), 0), np.zeros(n)]
        rows = draw.permutation(np.unique(np.stack([kinds[draw.integers(len(kinds))] for _ in range(m)], axis=1).astype(np.int32), axis=0))
        codes, nulls, ordered = [c.copy() for c in rows.T], [bool(x) for x in draw.integers(0, 2, m)], [bool(x) for x in draw.integers(0, 2, m)]
        form = compare.SlotForm([predicates.Slot((1, f"a{i}"), (2, f"a{i}"), o) for i, o in enumerate(ordered)], m)
        tally, left = compare.Tally(form.bits), None if trial % 2 else draw.random(len(rows)) < 0.5
        if left is None:
            compare.among(codes, nulls, form, tally)
        else:
            compare.across([c[left] for c in codes], [c[~left] for c in codes], nulls, form, tally)
        search = compare.Witnesses(codes, nulls, left, form)
        both = lambda seen: set(seen) | {search._turned(c) for c in seen}  # noqa: B023, E731
        assert both(search.run()) == both(tally.items())


def test_constraints_of_tens_of_billions_of_pairs_take_a_minute(spark):
    """One by one they took several minutes; a rising and an almost rising column have evidence that no pair shows."""
    df = spark.range(300_000).selectExpr("id as a", "id div 3 as b", "cast(id * 7919 % 20011 as double) as c", "cast(id % 13 as string) as d", "id + id * 37 % 5 as e")
    at = time.time()
    found = [r[0] for r in planner.denial_constraints(df, df.columns, "pair").collect()]
    assert time.time() - at < 60
    assert "t1.a = t2.a" in found and "t1.a <= t2.a and t1.b > t2.b" in found
