"""Near-copies against all pairs: no false link, and a measured recall."""

import random
import re

import pytest

from depmine.llm import near_copies
from test_text_ops import DOCS, none, odd, odd_rows  # noqa: F401


def word_sets(rows, size=5):
    out = {}
    for d, text in rows:
        words = re.findall(r"[^\x20\x09-\x0d]+", re.sub(r"[A-Z]", lambda m: m[0].lower(), text or ""))
        out[d] = frozenset(tuple(words[i : i + size]) for i in range(max(1, len(words) - size + 1))) if words else frozenset()
    return out


def slow_links(sets, similarity=0.8):
    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            x, y = sets[a], sets[b]
            if min(len(x), len(y)) >= similarity * max(len(x), len(y)) and len(x & y) >= similarity * len(x | y):
                yield a, b


def slow_classes(sets):
    label = {d: d for d in sets}

    def find(x):
        while label[x] != x:
            x = label[x]
        return x

    for a, b in slow_links(sets):
        x, y = find(a), find(b)
        label[max(x, y)] = min(x, y)
    return {d: find(d) for d in sets}


def test_equals_all_pairs_on_the_documents(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    want = slow_classes(word_sets([(r["doc_id"], r["text"]) for r in docs.collect()]))
    assert dict(map(tuple, near_copies.near_copies(docs).collect())) == want


@pytest.mark.parametrize("split_at", [4_000, 10])
def test_edited_copies(spark, split_at):
    """Copies with single words replaced; with tiny files the large groups go through pairs of blocks."""
    rng = random.Random(5)
    rows, planted = [], 0
    for g in range(60):
        words = [f"{rng.choice('abcdefgh')}{rng.randrange(3000)}" for _ in range(rng.randint(120, 400))]
        for copy in range(rng.randint(1, 6)):
            own = list(words)
            for _ in range(copy * len(words) // 120):
                own[rng.randrange(len(own))] = f"z{rng.randrange(3000)}"
            rows.append((len(rows), " ".join(own)))
    crowd = [f"c{i}" for i in range(400)]
    for i in range(40):  # one large file: the same long text with a word changed
        rows.append((len(rows), " ".join([*crowd[: i * 9], f"x{i}", *crowd[i * 9 + 1 :]])))
    frame = spark.createDataFrame([(d, t, None, None, None, 1, "x", "p", "q", "o") for d, t in rows], DOCS).repartition(4)
    got = dict(map(tuple, near_copies.near_copies(frame, split_at=split_at).collect()))
    sets = word_sets(rows)
    want, links = slow_classes(sets), list(slow_links(sets))
    assert set(got) == set(want) and all(want[d] == want[c] for d, c in got.items())
    joined = sum(got[a] == got[b] for a, b in links) / len(links)
    assert joined >= 0.98


def boilerplate(n, seed=3):
    """Texts of 300 words on one boilerplate, 4 to 8 words of each replaced: pairs lie around 0.8."""
    rng = random.Random(seed)
    plate = [f"p{i}" for i in range(300)]
    rows = []
    for i in range(n):
        own = list(plate)
        for k in range(rng.randint(4, 8)):
            own[rng.randrange(300)] = f"q{i}x{k}"
        rows.append((i, " ".join(own)))
    return rows


@pytest.mark.parametrize("split_at", [4_000, 30])
def test_one_boilerplate_around_the_similarity(spark, split_at):
    """Forest edges fail the similarity; the other pairs of the file are verified all the same."""
    rows = boilerplate(150)
    frame = spark.createDataFrame([(d, t, None, None, None, 1, "x", "p", "q", "o") for d, t in rows], DOCS).repartition(4)
    got = dict(map(tuple, near_copies.near_copies(frame, split_at=split_at).collect()))
    sets = word_sets(rows)
    want, links = slow_classes(sets), list(slow_links(sets))
    assert len(links) > 20
    assert all(want[d] == want[c] for d, c in got.items())
    assert all(got[a] == got[b] for a, b in links)


def test_short_and_long_texts_just_similar(spark):
    """Pairs of similarity 0.8 to 0.85, from 8 words upwards: none is lost."""
    rng = random.Random(7)
    rows = []
    for shingles in (4, 5, 6, 7, 9, 12, 20, 40, 100, 200):
        for pair in range(30):
            words = [f"w{rng.randrange(10**9)}" for _ in range(shingles + 4)]
            own = shingles // 4  # appended words: one new shingle each
            rows.append((len(rows), " ".join(words)))
            rows.append((len(rows), " ".join(words + [f"x{rng.randrange(10**9)}" for _ in range(own)])))
    sets = word_sets(rows)
    links = list(slow_links(sets))
    assert len(links) == 300
    assert all(0.8 <= len(sets[a] & sets[b]) / len(sets[a] | sets[b]) <= 0.88 for a, b in links)
    frame = spark.createDataFrame([(d, t, None, None, None, 1, "x", "p", "q", "o") for d, t in rows], DOCS).repartition(4)
    got = dict(map(tuple, near_copies.near_copies(frame).collect()))
    assert got == slow_classes(sets)


def test_odd_rows(odd, none):  # noqa: F811
    got = near_copies.near_copies(odd)
    want = slow_classes(word_sets([(r[0], r[1]) for r in odd_rows() if r[0] is not None]))
    assert sorted(map(tuple, got.collect())) == sorted((r[0], want[r[0]]) for r in odd_rows() if r[0] is not None)
    kept = near_copies.keep_one(odd)
    assert kept.columns == odd.columns
    assert sorted(r["doc_id"] for r in kept.collect() if r["doc_id"] is not None) == sorted(set(want.values()))
    assert near_copies.keep_one(odd).where("doc_id is null").count() == 1
    assert near_copies.keep_one(none).count() == near_copies.near_copies(none).count() == 0


def test_links_come_from_simhash(spark, monkeypatch):
    """Near fingerprints are linked by multi-index hashing, and near-copies follow from these links where no prefix file offers a pair."""
    words = [f"w{i}" for i in range(400)]
    texts = [" ".join(words), " ".join(words[:-1] + ["other"]), " ".join(reversed(words))]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    asked = []
    links = near_copies.simhash.links
    monkeypatch.setattr(near_copies.simhash, "links", lambda fps, *a, **o: (asked.append(fps.count()), links(fps, *a, **o))[1])
    monkeypatch.setattr(near_copies, "first_edges", lambda files, *a: files.where("false").selectExpr("key", "set_id as a", "n as b"))
    got = {r["doc_id"]: r["component_id"] for r in near_copies.near_copies(df).collect()}
    assert asked == [3] and got == {0: 0, 1: 0, 2: 2}


def test_a_file_hands_on_fewer_edges_than_texts():
    """Near-copies, and pairs just below the similarity, in one file: every pair is judged, the rows handed on do not grow with its square."""
    import numpy as np

    r = np.random.default_rng(1)
    base = r.integers(0, 1 << 63, 100).astype(np.uint64)
    sets = [np.unique(np.concatenate([base[c:], r.integers(0, 1 << 63, c).astype(np.uint64)])) for c in r.integers(4, 16, 120)]
    ids = np.arange(120)
    want = {i: i for i in range(120)}
    for i in range(120):
        for j in range(i):
            both = len(np.intersect1d(sets[i], sets[j]))
            if both / (len(sets[i]) + len(sets[j]) - both) >= 0.8 and want[i] != want[j]:
                low, high = sorted((want[i], want[j]))
                want = {k: low if v == high else v for k, v in want.items()}
    edges = near_copies.joining(ids, np.array([*map(len, sets)]), ids, [*map(near_copies.sketch, sets)], sets, 0.8)
    got = {i: i for i in range(120)}
    for a, b in edges:
        low, high = sorted((got[a], got[b]))
        assert low != high
        got = {k: low if v == high else v for k, v in got.items()}
    assert got == want and 1 < len(set(want.values())) < 120
