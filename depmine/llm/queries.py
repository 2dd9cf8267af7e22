"""The queries of the training-data operators, one for each, and their SQL where SQL can express them."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bigru, bpe_dp, hpylm, markov_secrets, shard, simhash, spaced_seeds, url_bloom, vafile, warc


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_simhash(spark, sf_dir):
    return simhash.near_duplicates(_table(spark, sf_dir, "documents")).select("doc_id", "fingerprint", "component_id")


def op2_vafile(spark, sf_dir):
    return vafile.search(_table(spark, sf_dir, "embeddings"), F.col("vec_id") % 100 == 0)


def op3_spaced_seeds(spark, sf_dir):
    return spaced_seeds.contaminated(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def op4_markov_secrets(spark, sf_dir):
    return markov_secrets.scan(_table(spark, sf_dir, "documents"))


def op5_warc(spark, sf_dir):
    back = warc.read_archives(warc.write_archives(_table(spark, sf_dir, "pages")))
    return back.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def listed_urls(spark, sf_dir) -> DataFrame:
    """The block list of op6: URLs of the pages whose document, named by the number in the path, is labelled toxic."""
    pages = _table(spark, sf_dir, "pages").select("url", F.regexp_extract(url_bloom.host_and_path(F.col("url"))[1], "/([0-9]{1,18})", 1).alias("number"))
    toxic = _table(spark, sf_dir, "labels").where("toxic = 1").select(F.col("doc_id").cast("string").alias("number")).distinct()
    return pages.join(toxic, "number", "left_semi").select("url")


def op6_url_bloom(spark, sf_dir):
    return url_bloom.judge(_table(spark, sf_dir, "pages"), listed_urls(spark, sf_dir)).drop("listed")


def op7_bigru(spark, sf_dir):
    docs = _table(spark, sf_dir, "documents")
    return bigru.identify(docs, bigru.train(docs))


def byte_ranks() -> tuple[dict[bytes, int], str]:
    return bpe_dp.read_ranks(public_tokenizers.path("byte_bpe_50k.tiktoken")), public_tokenizers.PATTERN


def op8_bpe_dp(spark, sf_dir):
    return bpe_dp.encode_documents(_table(spark, sf_dir, "documents"), *byte_ranks())


def op9_hpylm(spark, sf_dir):
    return hpylm.score(_table(spark, sf_dir, "documents"))


def op10_shard(spark, sf_dir):
    return shard.shard_documents(_table(spark, sf_dir, "documents"))


def queries():
    return {f.__name__: f for f in (op1_simhash, op2_vafile, op3_spaced_seeds, op4_markov_secrets, op5_warc, op6_url_bloom, op7_bigru, op8_bpe_dp, op9_hpylm, op10_shard)}


_OP2 = """
with v as (
  select vec_id, list_transform(embedding, lambda x: floor(1024 * cast(x as double))) as x from embeddings
  where embedding is not null and len(embedding) > 0 and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0
), scored as (
  select q.vec_id as query_id, c.vec_id, cast(list_dot_product(q.x, c.x) as bigint) as score
  from v q join v c on q.vec_id % 100 = 0 and q.vec_id <> c.vec_id
), ranked as (
  select query_id, cast(row_number() over (partition by query_id order by score desc, vec_id) as integer) as rank, vec_id, score from scored
)
select query_id, rank, vec_id, score from ranked where rank <= 10
"""

_OP5 = """
with p as (
  select page_id, strlen(coalesce(html, '')) as payload_bytes, sha1(coalesce(html, '')) as h from pages
), f as (
  select h, min(page_id) as first from p group by h
), d as (
  select h, list_aggregate(list_transform(range(40), lambda i: lpad(bin(instr('0123456789abcdef', substr(h, i + 1, 1)) - 1), 4, '0')), 'string_agg', '') as b from f
), e as (
  select h, list_aggregate(list_transform(range(32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
    1 + 16 * cast(substr(b, 5 * i + 1, 1) as int) + 8 * cast(substr(b, 5 * i + 2, 1) as int) + 4 * cast(substr(b, 5 * i + 3, 1) as int)
      + 2 * cast(substr(b, 5 * i + 4, 1) as int) + cast(substr(b, 5 * i + 5, 1) as int), 1)), 'string_agg', '') as payload_digest from d
)
select page_id, payload_bytes, payload_digest, case when page_id = first then 'response' else 'revisit' end as record_type,
  case when page_id <> first then first end as refers_to
from p join f using (h) join e using (h)
"""

_OP6 = r"""
with parts as (
  select page_id, url, case when instr(url, '://') > 0 then substr(url, instr(url, '://') + 3) end as rest from pages
), hp as (
  select page_id, url, coalesce(translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '') as host,
    coalesce(regexp_extract(rest, '^[^/?#]*([^?#]*)', 1), '') as path from parts
), c as (
  select *, array_to_string(list_sort(list_filter(string_split(coalesce(regexp_extract(url, '^[^?#]*\?([^#]*)', 1), ''), '&'),
      lambda a: a <> '' and not regexp_matches(a, '^(utm_[^=]*|ref)(=|$)'))), '&') as kept,
    regexp_replace(host, '^(www|m)\.', '') || regexp_replace(path, '/+$', '') as bare from hp
), canon as (
  select page_id, url, host, path, case when host = '' then null when kept = '' then bare else bare || '?' || kept end as canon from c
), listed as (
  select distinct canon from canon where canon is not null
    and regexp_extract(path, '/([0-9]{1,18})', 1) in (select cast(doc_id as varchar) from labels where toxic = 1)
), rules as (
  select * from (values ('org', '/', 'allow'), ('example.org', '/es/', 'block'), ('example.org', '/en/1', 'block'), ('com', '/fr/', 'allow'), ('com', '/de/', 'block')) t(h, p, v)
), fit as (
  select page_id, h || p as rule, v, row_number() over (partition by page_id order by length(h || p) desc) as n
  from canon join rules on (host = h or ends_with(host, '.' || h)) and starts_with(path, p)
)
select page_id, host, path, rule, coalesce(v, case when canon in (select canon from listed) then 'block' else 'allow' end) as verdict
from canon left join (select * from fit where n = 1) using (page_id)
"""


def oracle_sql():
    return {"op2_vafile": _OP2, "op5_warc": _OP5, "op6_url_bloom": _OP6}
