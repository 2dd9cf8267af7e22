"""The pipeline's stages, each held against what its own input should keep."""

import numpy as np
import pyarrow as pa
import public_tokenizers
import tiktoken

import corpus_pipeline
from depmine.llm import bpe_dp
from depmine.llm.common import BATCH_BYTES, thrifty
from test_near_copies import slow_classes, word_sets
from test_text_ops import slow_base


def test_stages(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    rows = {}
    frame = docs
    for name, stage in corpus_pipeline.STAGES:
        frame = stage(spark, frame, small)
        if name != corpus_pipeline.STAGES[-1][0]:
            assert set(frame.columns) == set(docs.columns)
            kept = frame.collect()
            frame = spark.createDataFrame(kept, docs.schema)
            rows[name] = {r["doc_id"]: r for r in kept}
            assert len(rows[name]) == len(kept)
    before = {r["doc_id"]: r for r in docs.collect()}
    gone = set(before) - set(rows["language"])
    assert all(not any(c.isalpha() for c in before[d]["text"]) or len(before[d]["text"]) < 2_000 for d in gone) and len(gone) < 0.03 * len(before)
    classes = slow_classes(word_sets([(d, r["text"]) for d, r in rows["language"].items()]))
    assert set(rows["near_duplicates"]) == set(classes.values())
    assert set(rows["decontamination"]) < set(rows["near_duplicates"])
    assert set(rows["secrets"]) == set(rows["decontamination"])
    assert not any(slow_base(r["text"].replace("[SECRET]", " ")) for r in rows["secrets"].values())
    assert all(r["n_chars"] == len(r["text"]) for r in rows["secrets"].values())
    ranks = bpe_dp.read_ranks(public_tokenizers.path("byte_bpe_50k.tiktoken"))
    reference = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    got = {r["doc_id"]: r["ids"] for r in frame.collect()}
    assert set(got) == set(rows["secrets"])
    assert all(np.array_equal(got[d], reference.encode_ordinary(r["text"])) for d, r in rows["secrets"].items())


def test_odd_rows_through_all_stages(spark, small, tmp_path):
    """Nulls in every column, empty and very long texts, repeated rows, an empty benchmark, and extra columns with the operators' own names."""
    plain = "the committee met in the morning and agreed on a plan for the library and its many readers in town today"
    other = "a different story of rain and rivers that nobody in the valley had told before the long dry summer ended"
    long = " ".join(f"word{i % 991}x{i}" for i in range(60_000))
    rows = [(1, plain, "en", "s", 9), (1, plain, "en", "s", 9), (2, plain, None, None, None), (3, None, "en", "s", 1), (4, "", None, "s", 0), (5, "123 456 !!", None, "s", 1), (None, other + " api_key = 'Zx81kQpL0a9s'", None, None, None), (6, other, "en", None, None), (7, long, "en", "s", 1), (8, long + " end", "en", "s", 1)]
    frame = spark.createDataFrame([(*r, "k", 1, "x", 2) for r in rows], "doc_id long, text string, lang string, source string, n_chars long, key string, fp int, hash string, shift int").repartition(3)
    spark.createDataFrame([], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    kept = {}
    for name, stage in corpus_pipeline.STAGES:
        frame = stage(spark, frame, str(tmp_path))
        kept[name] = frame.collect()
        if name != "tokens":
            assert frame.columns == list(corpus_pipeline.COLUMNS)
            frame = spark.createDataFrame(kept[name], frame.schema)
    ids = lambda name: sorted((r["doc_id"] is None, r["doc_id"]) for r in kept[name])
    assert ids("language") == [(False, i) for i in (1, 1, 2, 6, 7, 8)] + [(True, None)]
    assert ids("near_duplicates") == [(False, 1), (False, 6), (False, 7), (True, None)] == ids("decontamination")
    assert {r["text"][-8:] for r in kept["secrets"] if r["doc_id"] is None} == {"SECRET]'"} and all(r["lang"] == "en" and r["n_chars"] == len(r["text"]) for r in kept["secrets"])
    assert ids("tokens") == ids("secrets")


def test_empty_documents(spark, small):
    frame = spark.read.parquet(f"{small}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        frame = stage(spark, frame, small)
    assert frame.count() == 0


def test_no_stage_moves_many_whole_texts_at_once(spark):
    """Batches of 10,000 whole texts took an executor over its memory; every stage with Python workers bounds their bytes."""
    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    texts = spark.range(200, numPartitions=1).selectExpr("id as doc_id", "repeat(concat('word', id, ' '), 12500) as text", "'en' as lang", "cast(null as string) as source", "100000L as n_chars")
    before = spark.conf.get(name)
    try:
        for _, stage in (s for s in corpus_pipeline.STAGES if s[0] in ("near_duplicates", "tokens")):
            spark.conf.set(name, str(64 << 20))
            stage(spark, texts, "")
            largest = texts.mapInArrow(thrifty(lambda batches: (pa.RecordBatch.from_arrays([pa.array([b.nbytes])], ["n"]) for b in batches)), "n long").agg({"n": "max"}).first()[0]
            assert 0 < largest <= 2 * BATCH_BYTES
    finally:
        spark.conf.set(name, before)
