"""URL filter: host and path rules first, then a blocked Bloom filter before an exact join, in DataFrame functions only.

Listed URLs set four bits in one 64-bit word of the filter; words are joined by
`bit_or`. A page's canonical URL is looked up in its one word, and only possible
hits go on to the hash join with the list, which removes the false ones. The
filter always has 16 bits an entry. Up to `told_words` words (16 bytes each) it is
broadcast; a larger one meets the pages by an exchange on the word's number.

Canonical form: scheme and a leading `www.` or `m.` dropped, host in lower case,
without fragment, `utm_` and `ref` arguments and trailing slashes; other arguments in order of their text.
Defined results: a null URL, or one without `://`, has empty host and path,
meets no rule and is allowed; repeated rows are each judged; list entries may
repeat or be null; an empty table or list works; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialize

#: Fixed rules (host, path, verdict).
RULES = (("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block"))


def host_and_path(url: Column) -> tuple[Column, Column]:
    rest = F.when(F.locate("://", url) > 0, F.substring(url, F.locate("://", url) + 3, F.length(url)))
    host = F.translate(F.regexp_extract(rest, r"^[^/?#]*", 0), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    return F.coalesce(host, F.lit("")), F.coalesce(path, F.lit(""))


def canonical(url: Column) -> Column:
    host, path = host_and_path(url)
    query = F.regexp_extract(url, r"^[^?#]*\?([^#]*)", 1)
    kept = F.array_join(F.array_sort(F.filter(F.split(query, "&"), lambda a: (a != "") & ~a.rlike(r"^(utm_[^=]*|ref)(=|$)"))), "&")
    bare = F.concat(F.regexp_replace(host, r"^(www|m)\.", ""), F.regexp_replace(path, "/+$", ""))
    return F.when(host == "", F.lit(None)).otherwise(F.when(kept == "", bare).otherwise(F.concat(bare, F.lit("?"), kept)))


def rule_for(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """The longest rule that fits, and its verdict; null where none fits."""
    rule = verdict = F.lit(None).cast("string")
    for h, p, v in sorted(rules, key=lambda r: len(r[0] + r[1])):
        fits = ((host == h) | host.endswith(f".{h}")) & path.startswith(p)
        rule, verdict = F.when(fits, F.lit(h + p)).otherwise(rule), F.when(fits, F.lit(v)).otherwise(verdict)
    return rule, verdict


def _word_and_bits(canon: Column, words: int) -> tuple[Column, Column]:
    h, bits = F.xxhash64(canon), F.xxhash64(canon, F.lit(1))
    one = F.lit(1).cast("long")
    mask = F.lit(0).cast("long")
    for i in range(4):
        place = F.shiftrightunsigned(bits, 6 * i).bitwiseAND(F.lit(63).cast("long")).cast("int")
        mask = mask.bitwiseOR(F.call_function("shiftleft", one, place))
    return F.pmod(h, F.lit(words).cast("long")), mask


def build_filter(listed: DataFrame, words: int) -> DataFrame:
    """(word_no, word) of the distinct canonical URLs in column canon."""
    no, mask = _word_and_bits(F.col("canon"), words)
    return listed.select(no.alias("word_no"), mask.alias("mask")).groupBy("word_no").agg(F.bit_or("mask").alias("word"))


def filter_words(n_listed: int, bits_each: int = 16) -> int:
    return max(1, -(-n_listed * bits_each // 64))


def judge(pages: DataFrame, listed: DataFrame, rules=RULES, id_col: str = "page_id", url_col: str = "url", told_words: int = 1 << 20) -> DataFrame:
    """page_id, host, path, rule, verdict, listed. `listed`: column url; a listed URL no rule settles is blocked, all others allowed."""
    distinct = materialize(listed.select(canonical(F.col("url")).alias("canon")).where("canon is not null").distinct(), "listed")
    words = filter_words(distinct.count())
    host, path = host_and_path(F.col("url"))
    rule, verdict = rule_for(F.col("host"), F.col("path"), rules)
    rows = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url")).select("page_id", "url", host.alias("host"), path.alias("path"))
    rows = rows.select("page_id", "host", "path", rule.alias("rule"), verdict.alias("ruled"), canonical(F.col("url")).alias("canon"))
    no, mask = _word_and_bits(F.col("canon"), words)
    table = build_filter(distinct, words)
    table = F.broadcast(table) if words <= told_words else materialize(table, "filter")  # two longs a word; read back, so that a hot word's partition can be split
    probed = rows.withColumn("word_no", no).withColumn("mask", mask).join(table, "word_no", "left")
    possible = F.coalesce(F.col("word").bitwiseAND(F.col("mask")) == F.col("mask"), F.lit(False)) & F.col("ruled").isNull()
    probed = probed.withColumn("key", F.when(possible, F.col("canon")))
    exact = distinct.select(F.col("canon").alias("entry"))
    hits = probed.where("key is not null").join(exact, F.col("key") == F.col("entry"), "left")
    out = hits.unionByName(probed.where("key is null").withColumn("entry", F.lit(None).cast("string")))
    found = F.col("entry").isNotNull()
    return out.select("page_id", "host", "path", "rule", F.coalesce("ruled", F.when(found, "block").otherwise("allow")).alias("verdict"), found.alias("listed"))
