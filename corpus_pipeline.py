"""From raw documents to token ids: five stages, each on all that the one before kept.

Every stage but the last returns the columns of `documents`. Rejected: texts
without a language, all but one document of each near-duplicate group, and
documents that overlap a benchmark item. Secrets are cut out of texts that stay.

Defined results. Null, empty and letterless texts have no language and go in
the first stage, as does everything if no row names a language to learn from.
A row without doc_id is judged by its text: the language, benchmark and secret
stages treat it like any other, the near-duplicate stage keeps it. Of repeated rows and
of ties the near-duplicate stage keeps one, that with the smallest doc_id. Null lang is filled
in, null source stays, n_chars follows the text once secrets are cut out. Texts of any
length are read whole. Columns besides those of `documents` are dropped, whatever
their names. Empty documents give an empty result; without benchmark items nothing is contaminated.

Rows go to Python in batches of at most `common.BATCH_BYTES`, a setting that the session keeps; no result depends on it.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from depmine.llm import bigru, bpe_dp, markov_secrets, near_copies, spaced_seeds
from depmine.llm.common import give_back, materialize, short_batches
from depmine.llm.queries import byte_ranks

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
#: A text whose best language gets less than this share of its bytes has none.
LEAST_SHARE = 0.3


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts with a language stay; a missing lang is filled in."""
    short_batches(spark)
    net = bigru.train(docs)
    give_back()
    found = bigru.identify(docs, net, keep=("text", "lang", "source", "n_chars"))
    stay = found.where((F.col("lang_pred") != bigru.UND) & (F.col("score") >= LEAST_SHARE))
    return stay.withColumn("lang", F.coalesce("lang", "lang_pred")).select(*COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near-duplicates (five-word shingles, similarity 0.8) the document with the smallest id stays."""
    short_batches(spark)
    return near_copies.keep_one(docs).select(*COLUMNS)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark passage go."""
    short_batches(spark)
    return spaced_seeds.decontaminate(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")).select(*COLUMNS)


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are replaced by a mark; n_chars follows the text."""
    return markov_secrets.redact(docs).withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every text, with the digests of ids and decoded bytes."""
    short_batches(spark)
    return bpe_dp.encode_documents(docs, *byte_ranks(), with_ids=True, keep=("lang", "source"))


STAGES = [("language", language), ("near_duplicates", near_duplicates), ("decontamination", decontamination), ("secrets", secrets), ("tokens", tokens)]

#: SQL cannot express the trained models, fingerprints and tokens; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
