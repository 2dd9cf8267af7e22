"""Search, archives, URL filter and shards against brute force, and their defined results in odd cases."""

import base64
import collections
import hashlib
import io
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from depmine.llm import queries, shard, url_bloom, vafile, warc


# -- vectors ------------------------------------------------


def slow_search(rows, k=10):
    good = [(i, np.floor(1024 * np.array(v, np.float64)).astype(int)) for i, v in rows if i is not None and v and all(x is not None and np.isfinite(x) for x in v)]
    out = set()
    for q, x in {i: v for i, v in good if i % 100 == 0}.items():
        ranked = sorted(((-int(x[: len(v)] @ v[: len(x)]), i) for i, v in good if i != q))[:k]
        out |= {(q, n, i, -s) for n, (s, i) in enumerate(ranked, 1)}
    return out


@pytest.mark.parametrize("size", [32 << 20, 500])
def test_search_equals_brute_force(spark, size):
    rng = np.random.default_rng(1)
    rows = [(i, (rng.standard_normal(16) * 0.2).round(1 + i % 3).tolist()) for i in range(700)]
    rows += [(1000 + i, rows[5][1]) for i in range(300)] + [(None, [0.1] * 16), (7001, None), (7100, []), (7200, [float("nan")] * 16), (7300, [None] * 16), (7400, [float("inf")] * 16), (7500, [0.5, 0.25]), (7600, [90.0] * 16)]
    frame = spark.createDataFrame([(i, v, 1, 2) for i, v in rows], "vec_id long, embedding array<float>, score int, cells int").repartition(5)
    rows = [(i, None if v is None else [None if x is None else float(np.float32(x)) for x in v]) for i, v in rows]
    got = vafile.search(frame, F.col("vec_id") % 100 == 0, query_bytes=size, seeds=64).collect()
    assert {tuple(r) for r in got} == slow_search(rows) and len(got) == len(set(got))


def test_scores_beyond_53_bits(spark):
    """Components of 2^21 and more times 1024: products that floating point would round."""
    rows = [(i, [float(2**21 + i), float(2**20 + 3 * i), 1.0 + i / 1024]) for i in range(0, 400, 5)]
    got = vafile.search(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), F.col("vec_id") % 100 == 0).collect()
    good = {i: [int(np.floor(1024 * x)) for x in v] for i, v in rows}
    want = set()
    for q in (i for i in good if i % 100 == 0):
        ranked = sorted((-sum(a * b for a, b in zip(good[q], good[i])), i) for i in good if i != q)[:10]
        want |= {(q, n, i, -s) for n, (s, i) in enumerate(ranked, 1)}
    assert {tuple(r) for r in got} == want and max(s for *_, s in want) > 2**53
    huge = spark.createDataFrame([(0, [1e18]), (1, [1e18])], "vec_id long, embedding array<double>")
    with pytest.raises(Exception, match="exceeds 64 bits"):
        vafile.search(huge, F.col("vec_id") == 0).collect()


def test_only_survivors_are_read():
    """Most vectors are ruled out by their cells."""
    rng = np.random.default_rng(2)
    vectors = (rng.standard_normal((4000, 64)) * 128).astype(np.int64)
    table = lambda v, first: pa.table({"vec_id": np.arange(first, first + len(v)), "exact": pa.array(v.tolist(), pa.list_(pa.int64()))})
    block = vafile.Block(table(vectors[:20], 0), table(vectors[:500], 0), 10, 8)
    cells = [c.astype(np.int8).tobytes() for c in vectors // 8]
    batch = pa.RecordBatch.from_arrays([pa.array(np.arange(4000)), pa.array(np.arange(4000)), pa.array(cells, pa.binary())], ["row", "vec_id", "cells"])
    found = pa.Table.from_batches(list(block.scan([batch])))
    assert 20 * 10 <= found.num_rows < 0.1 * 20 * 4000


def test_search_of_nothing(spark):
    none = spark.createDataFrame([], "vec_id long, embedding array<float>")
    assert vafile.search(none, F.col("vec_id") % 100 == 0).count() == 0


# -- archives ------------------------------------------------

PAGES = "page_id long, url string, html string, sha string, first int, path string"


def page_rows():
    html = [None, "", "<p>a</p>", "<p>a</p>", "é" * 200_000, "<p>a</p>\r\n\r\nx", "<b>"]
    rows = [(i, f"http://h.example/{i}\nx é" if i else None, h, "s", 1, "p") for i, h in enumerate(html)]
    return rows + [rows[2], rows[6], (None, "u", "<p>a</p>", "s", 1, "p"), (None, None, "alone", "s", 1, "p")]


def test_archives_round_trip(spark, tmp_path):
    frame = spark.createDataFrame(page_rows(), PAGES).repartition(3)
    back = warc.read_archives(warc.write_archives(frame, f"file://{tmp_path}/a", roll_bytes=2_000), payloads=True).collect()
    least = {}
    for i, _, h, *_ in page_rows():
        if i is not None:
            least[h or ""] = min(i, least.get(h or "", i))
    want = collections.Counter()
    for i, _, h, *_ in page_rows():
        h = h or ""
        refers = least.get(h) if least.get(h) != i else None
        want[(i, len(h.encode()), base64.b32encode(hashlib.sha1(h.encode()).digest()).decode(), "response" if refers is None else "revisit", refers, None if refers is not None else h.encode())] += 1
    assert want == collections.Counter((r["page_id"], r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"], None if r["payload"] is None else bytes(r["payload"])) for r in back)
    none = spark.createDataFrame([], PAGES)
    assert warc.read_archives(warc.write_archives(none)).count() == 0


@pytest.mark.parametrize("told", [200_000, 0])
def test_one_payload_on_most_pages(spark, tmp_path, monkeypatch, told):
    """Both ways to find a repeated payload's first page; the common one is split over tasks."""
    monkeypatch.setattr(warc, "TOLD", told)
    frame = spark.range(12_000).select(F.col("id").alias("page_id"), F.lit("u").alias("url"), F.when(F.col("id") % 10 == 0, F.concat(F.lit("<p>"), F.floor(F.col("id") / 20))).otherwise("<same>").alias("html"))
    got = warc.read_archives(warc.write_archives(frame, f"file://{tmp_path}/b")).groupBy("record_type").count().collect()
    assert dict(map(tuple, got)) == {"response": 601, "revisit": 11_399}


def test_archive_holds_its_dictionary(spark, small):
    manifest = warc.write_archives(spark.read.parquet(f"{small}/pages.parquet")).collect()
    shared, place = warc.file_system(manifest[0]["path"])
    data = shared.open_input_stream(place, compression=None).read()
    assert int.from_bytes(data[:4], "little") == warc.DICTIONARY_FRAME
    records = list(warc.read_archive(io.BytesIO(data)))
    assert len(records) == manifest[0]["records"] and all(r.startswith(b"WARC/1.1\r\n") and r.endswith(b"\r\n\r\n") for r in records)
    with pytest.raises(EOFError):
        list(warc.read_archive(io.BytesIO(data[:-3])))


# -- URLs ------------------------------------------------


def test_urls(spark):
    urls = [(0, None), (1, ""), (2, "no scheme"), (3, "http://A.Example.ORG/es/x"), (4, "http://example.org"), (5, "http://example.org/en/12?q"), (6, "https://x.com/fr/1"), (7, "https://x.com/de/#f"), (8, "https://x.com/it/7?utm_source=a&b=1#t"), (9, "https://www.x.com/it/7/?b=1"), (10, "ftp://notorg/"), (11, "http://evil.net?x"), (11, "http://evil.net?x"), (12, "http://evil.net/y"), (None, "http://evil.net#z")]
    pages = spark.createDataFrame([(i, u, "x", "y") for i, u in urls], "page_id long, url string, word string, canon string")
    listed = spark.createDataFrame([("https://m.x.com/it/7?b=1&ref=q",), ("http://evil.net",), (None,), ("http://evil.net?x",)], "url string")
    got = {(r["page_id"], r["host"], r["path"], r["rule"], r["verdict"]) for r in url_bloom.judge(pages, listed).collect()}
    assert got == {
        (0, "", "", None, "allow"), (1, "", "", None, "allow"), (2, "", "", None, "allow"),
        (3, "a.example.org", "/es/x", "example.org/es/", "block"), (4, "example.org", "", None, "allow"),
        (5, "example.org", "/en/12", "example.org/en/1", "block"), (6, "x.com", "/fr/1", "com/fr/", "allow"), (7, "x.com", "/de/", "com/de/", "block"),
        (8, "x.com", "/it/7", None, "block"), (9, "www.x.com", "/it/7/", None, "block"), (10, "notorg", "/", None, "allow"),
        (11, "evil.net", "", None, "block"), (12, "evil.net", "/y", None, "allow"), (None, "evil.net", "", None, "block"),
    }
    assert url_bloom.judge(pages, listed).count() == len(urls)
    assert {r["verdict"] for r in url_bloom.judge(pages.where("page_id > 8"), listed.limit(0)).collect()} == {"allow"}
    assert url_bloom.judge(pages.limit(0), listed).count() == 0


def test_filter_by_exchange(spark, small):
    """A filter too large to broadcast meets the pages by the number of its word."""
    pages, listed = spark.read.parquet(f"{small}/pages.parquet"), queries.listed_urls(spark, small)
    a, b = (sorted(map(str, url_bloom.judge(pages, listed, told_words=n).collect())) for n in (0, 1 << 20))
    assert a == b and any("block" in x for x in a)


def test_large_list(spark):
    """A list of two million URLs keeps its 16 bits an entry: few pages that are not listed pass the filter."""
    listed = spark.range(2_000_000).select(F.concat(F.lit("http://l.example/"), "id").alias("url"))
    canon = listed.select(url_bloom.canonical(F.col("url")).alias("canon"))
    words = url_bloom.filter_words(2_000_000)
    no, mask = url_bloom._word_and_bits(url_bloom.canonical(F.col("url")), words)
    others = spark.range(20_000).select(F.concat(F.lit("http://o.example/"), "id").alias("url"))
    passed = others.select(no.alias("word_no"), mask.alias("mask")).join(url_bloom.build_filter(canon, words), "word_no").where("word & mask = mask").count()
    assert words == 500_000 and passed < 0.02 * 20_000


def test_pages_of_an_argument_are_told_apart(spark):
    pages = spark.createDataFrame([(1, "http://a.b/x?page=1"), (2, "http://a.b/x?page=2")], "page_id long, url string")
    listed = spark.createDataFrame([("http://a.b/x?page=1",)], "url string")
    assert {r["page_id"]: r["verdict"] for r in url_bloom.judge(pages, listed).collect()} == {1: "block", 2: "allow"}


# -- shards ------------------------------------------------


def test_hypergeometric_law():
    rng = np.random.default_rng(1)
    for good, bad, take in ((10**10, 3 * 10**10, 10**9), (2 * 10**9, 5, 10**9)):
        draws = np.array([shard.hypergeometric(rng, good, bad, take) for _ in range(400)], float)
        n, p = good + bad, good / (good + bad)
        spread = (take * p * (1 - p) * (n - take) / (n - 1)) ** 0.5
        assert abs(draws.mean() - take * p) < 5 * spread / 20 + 1e-9 and (spread < 2 or 0.8 < draws.std() / spread < 1.2)


def test_matrix_adds_up():
    rows, sizes = [5, 0, 100, 37, 1], [n for *_, n in shard.slot_ranges(143, 6, 10)]
    matrix = np.array([shard.matrix_row(np.cumsum(rows).tolist(), sizes, p, 9) for p in range(5)])
    assert matrix.sum(axis=1).tolist() == rows and matrix.sum(axis=0).tolist() == sizes


def test_shuffle_is_uniform(spark):
    frame = spark.range(0, 6, numPartitions=3)
    seen = collections.Counter()
    for seed in range(50):
        for r in shard.shuffle(frame, 3, seed, range_rows=1).collect():
            seen[(r["id"], r["shard"], r["slot"])] += 1
    assert len(seen) == 36 and max(seen.values()) < 26 and min(seen.values()) > 0


def test_shards(spark, small):
    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{small}/documents.parquet").collect()}
    got = queries.op10_shard(spark, small).collect()
    assert {r["doc_id"]: (r["size"], r["text_crc32"]) for r in got} == {d: (len(t.encode()) + 8, zlib.crc32(t.encode())) for d, t in texts.items()}
    slots = collections.defaultdict(list)
    for r in got:
        slots[r["shard"]].append(r["slot"])
    assert sorted(slots) == list(range(24)) and all(sorted(s) == list(range(len(s))) for s in slots.values())
    assert max(map(len, slots.values())) - min(map(len, slots.values())) <= 1
    odd = spark.createDataFrame([(1, None, 1), (1, None, 1), (None, "", 2), (3, "é" * 100_000, 3)], "doc_id long, text string, shard int")
    assert sorted(r["size"] for r in shard.shard_documents(odd).collect()) == [8, 8, 8, 200_008]
    assert shard.shard_documents(odd.limit(0)).count() == 0
    assert shard.shuffle(odd, 2).columns == ["doc_id", "text", "shard", "slot"] and {r["shard"] for r in shard.shuffle(odd, 2).collect()} == {0, 1}
