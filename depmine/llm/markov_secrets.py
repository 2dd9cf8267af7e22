"""Secret scan by two character Markov models, in DataFrame functions only.

Known formats are found by patterns. Beyond them, long unbroken strings are
scored by two first-order models of characters, one of random strings and one
of ordinary identifiers; a string whose mean log-likelihood ratio for each
character exceeds the threshold is reported as kind `markov`. Both models are
trained from labelled samples: generated digests and the values the patterns
find on one side, the words of the texts on the other. The sample of texts is
bounded by `sample_docs`; a model is a table over pairs of ASCII characters, so its size is fixed.

Defined results: a null text counts as empty; an empty text has no spans and
the digest of the empty string; repeated rows are each scanned; offsets are
code points, end exclusive; added spans never overlap pattern spans; an empty
table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Fixed patterns, in the order in which kinds are listed.
ASSIGN = r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{16,}"
HEX = r"[0-9a-f]{24,}"
KINDS = ("assign", "access", "hex", "markov")
#: Strings that the models judge.
CANDIDATE = r"[A-Za-z0-9+/_=-]{20,}"
WORD = r"[A-Za-z][A-Za-z0-9_-]{4,}"
SPAN = "array<struct<start:long,kind_no:int,stop:long,value:string>>"


#: Hits and spans are folded in blocks of so many, for which arrays grow, and texts cut in pieces of so many characters: work stays near linear in a text.
FOLDED, PIECE = 256, 4096


def _folded(items: Column, begin: Column, kind: str, step) -> Column:
    """The array that step(acc, item) -> (at, own array to append) makes, folded block by block; begin: struct (at, found)."""
    blocks = F.transform(F.sequence(F.lit(0), F.floor((F.size(items) - 1) / FOLDED).cast("int")), lambda b: F.slice(items, b * FOLDED + 1, F.lit(FOLDED)))
    none = F.from_json(F.lit("[]"), kind)

    def one(acc, item):
        at, more = step(acc["at"], item)
        return F.struct(at.alias("at"), F.concat(acc["found"], more).alias("found"))

    def block(acc, items):
        inner = F.array(F.aggregate(items, F.struct(acc["at"].alias("at"), none.alias("found")), one))  # as an element, so that it is made once
        return F.get(F.transform(inner, lambda x: F.struct(x["at"].alias("at"), F.concat(acc["found"], x["found"]).alias("found"))), F.lit(0))

    return F.when(F.size(items) > 0, F.aggregate(blocks, F.struct(begin.alias("at"), none.alias("found")), block)["found"]).otherwise(none)


def _paired(text: Column, pattern: str, hits: Column) -> Column:
    """Each hit with what stands between it and the one before."""
    gaps = F.split(text, pattern, -1)
    return F.when(F.size(hits) > 0, F.zip_with(F.slice(gaps, 1, F.size(hits)), hits, lambda gap, hit: F.struct(F.length(gap).alias("gap"), hit.alias("hit")))).otherwise(F.from_json(F.lit("[]"), "array<struct<gap:int,hit:string>>"))


def _located(pairs: Column, kind_no: int) -> Column:
    """The hits with their offsets: each begins where the one before and the gap end."""

    def step(at, pair):
        start = at + pair["gap"]
        stop = start + F.length(pair["hit"])
        return stop, F.array(F.struct(start.alias("start"), F.lit(kind_no).alias("kind_no"), stop.alias("stop"), pair["hit"].alias("value")))

    return _folded(pairs, F.lit(0).cast("long"), SPAN, step)


def with_spans(df: DataFrame, patterns) -> DataFrame:
    """Adds __spans0, ... of the patterns over __text, given as (kind number, pattern). Hits, pairs and spans are columns of their own, so that each is made once a row."""
    out = df
    for n, pattern in patterns:
        out = out.withColumn(f"__hits{n}", F.regexp_extract_all("__text", F.lit(pattern), F.lit(0)))
    for n, pattern in patterns:
        out = out.withColumn(f"__pairs{n}", _paired(F.col("__text"), pattern, F.col(f"__hits{n}")))
    for n, _ in patterns:
        out = out.withColumn(f"__spans{n}", _located(F.col(f"__pairs{n}"), n))
    return out.drop(*[f"__{x}{n}" for x in ("hits", "pairs") for n, _ in patterns])


def with_base_spans(df: DataFrame, text_col: str) -> DataFrame:
    """Adds __text and __base: the spans of the fixed patterns by start, then kind."""
    out = with_spans(df.withColumn("__text", F.coalesce(F.col(text_col), F.lit(""))), list(enumerate((ASSIGN, ACCESS, HEX))))
    kept = F.filter("__spans0", lambda s: F.length(F.regexp_extract(s["value"], ASSIGN, 2)) >= 6)
    return out.withColumn("__base", F.array_sort(F.concat(kept, F.col("__spans1"), F.col("__spans2")))).drop("__spans0", "__spans1", "__spans2")


def _neighbours(value: Column) -> Column:
    """Each two neighbouring characters of a string, in one pass over it."""
    chars = F.split(value, "")
    return F.zip_with(F.slice(chars, 1, F.length(value) - 1), F.slice(chars, 2, F.length(value) - 1), lambda a, b: F.concat(a, b))


def _pairs(strings: DataFrame) -> DataFrame:
    """Counts of neighbouring characters over the column value."""
    return strings.where(F.length("value") > 1).select(F.explode(_neighbours(F.col("value"))).alias("pair")).groupBy("pair").count()


def train(df: DataFrame, text_col: str = "text", id_col: str = "doc_id", sample_docs: int = 400, generated: int = 2_000, smoothing: float = 0.2) -> list[float]:
    """128 x 128 log-likelihood ratios of a character after another: random strings over identifiers. The sample is drawn by a hash of id and text, equal ones once: about sample_docs rows."""
    spark = df.sparkSession
    rows = df.count()
    drawn = F.xxhash64(F.col(id_col), F.col(text_col))
    share = F.pmod(drawn, F.lit(max(1, rows))) < sample_docs
    sample = with_base_spans(df.where(share).select(F.col(text_col).alias("text"), drawn.alias("__drawn")).dropDuplicates(["__drawn"]), "text")
    digest = F.sha2(F.col("id").cast("string"), 512)
    made = spark.range(generated).select(F.explode(F.array(F.base64(F.unhex(digest)), F.lower(F.base64(F.unhex(digest))), F.upper(F.base64(F.unhex(digest))), digest)).alias("value"))
    known = sample.select(F.explode("__base").alias("s")).select(F.when(F.col("s.kind_no") == 0, F.regexp_extract("s.value", ASSIGN, 2)).otherwise(F.col("s.value")).alias("value"))
    bare = F.regexp_replace(F.regexp_replace(F.regexp_replace("__text", ASSIGN, " "), ACCESS, " "), HEX, " ")
    words = sample.select(F.explode(F.regexp_extract_all(bare, F.lit(WORD), F.lit(0))).alias("value"))
    counts = _pairs(made.unionByName(known)).select(F.lit(0).alias("model"), "*").unionByName(_pairs(words).select(F.lit(1).alias("model"), "*"))
    seen = [[[0.0] * 128 for _ in range(128)] for _ in range(2)]
    for r in counts.where(F.col("pair").rlike(r"^[\x21-\x7e]{2}$")).collect():  # at most 2 x 94 x 94 rows
        seen[r["model"]][ord(r["pair"][0])][ord(r["pair"][1])] += r["count"]

    def logs(table):
        return [[math.log((c + smoothing) / (sum(row) + smoothing * 94)) for c in row] for row in table]

    return [a - b for x, y in zip(logs(seen[0]), logs(seen[1])) for a, b in zip(x, y)]


def mean_ratio(value: Column, model: list[float]) -> Column:
    """Mean log-likelihood ratio of a string's characters, in one pass over it."""
    table = F.split(F.lit(",".join(str(round(x, 4)) for x in model[33 * 128 :])), ",").cast("array<double>")  # one constant: thousands of literals would slow planning down
    codes = F.transform(F.split(value, ""), lambda c: F.ascii(c))
    n = F.length(value) - 1
    steps = F.zip_with(F.slice(codes, 1, n), F.slice(codes, 2, n), lambda a, b: F.get(table, (a - 33) * 128 + b))
    return F.aggregate(steps, F.lit(0.0), lambda acc, x: acc + x) / n


def find_secrets(df: DataFrame, text_col: str = "text", id_col: str = "doc_id", model: list[float] | None = None, threshold: float = 0.8, sample_docs: int = 400) -> DataFrame:
    """df with __base and __all: arrays of (start, kind_no, stop, value) by start, then kind."""
    model = model or train(df, text_col, id_col, sample_docs)
    out = with_spans(with_base_spans(df, text_col), [(3, CANDIDATE)])

    def ahead(at, s):
        """Spans by start: a candidate goes if a base span before it reaches into it."""
        base = s["kind_no"] < 3
        return F.when(base, F.greatest(at, s["stop"])).otherwise(at), F.when(base | (s["start"] >= at), F.array(s)).otherwise(F.slice(F.array(s), 1, 0))

    def behind(at, s):
        """Spans from the last: a candidate goes if a base span behind its start begins within it, or if it is not random enough."""
        base = s["kind_no"] < 3
        kept = base | (s["stop"] <= at) & (mean_ratio(s["value"], model) > threshold)
        return F.when(base, F.least(at, s["start"])).otherwise(at), F.when(kept, F.array(s)).otherwise(F.slice(F.array(s), 1, 0))

    out = out.withColumn("__both", F.when(F.size("__spans3") > 0, F.array_sort(F.concat("__base", "__spans3"))).otherwise(F.from_json(F.lit("[]"), SPAN)))
    out = out.withColumn("__left", F.reverse(_folded(F.col("__both"), F.lit(0).cast("long"), SPAN, ahead)))
    out = out.withColumn("__kept", F.array_sort(_folded(F.col("__left"), F.lit(1 << 62).cast("long"), SPAN, behind)))
    return out.withColumn("__all", F.when(F.size("__spans3") > 0, F.col("__kept")).otherwise(F.col("__base"))).drop("__spans3", "__both", "__left", "__kept")


def spelled(spans: Column) -> Column:
    """kind:start:stop, comma-joined."""
    kinds = F.array(*map(F.lit, KINDS))
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(kinds, s["kind_no"]), s["start"].cast("string"), s["stop"].cast("string"))), ",")


def scan(df: DataFrame, text_col: str = "text", id_col: str = "doc_id", **options) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_markov."""
    n = lambda column, kind: F.size(F.filter(column, lambda s: s["kind_no"] == kind)).cast("long")
    found = find_secrets(df.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")), "text", "doc_id", **options)
    return found.select("doc_id", *[n("__base", i).alias(f"n_{KINDS[i]}") for i in range(3)], F.sha2(spelled(F.col("__base")), 256).alias("base_sha256"), spelled(F.col("__all")).alias("spans"), n("__all", 3).alias("n_markov"))


def redact(df: DataFrame, text_col: str = "text", id_col: str = "doc_id", mark: str = "[SECRET]", **options) -> DataFrame:
    """df with every span of the text replaced by the mark, spans that overlap by one; null texts stay null."""
    found = find_secrets(df, text_col, id_col, **options).withColumn("__pieces", F.regexp_extract_all("__text", F.lit(f"(?s).{{1,{PIECE}}}"), F.lit(0)))

    def between(start, stop):
        """Characters start to stop of the text, read from its pieces."""
        first, last = F.floor(start / PIECE).cast("int"), F.floor((stop - 1) / PIECE).cast("int")
        near = F.array_join(F.slice("__pieces", first + 1, F.greatest(last - first + 1, F.lit(0))), "")
        return F.substring(near, (start % PIECE + 1).cast("int"), (stop - start).cast("int"))

    def step(at, s):
        more = s["start"] >= at
        return F.greatest(at, s["stop"]), F.when(more, F.array(F.concat(F.when(s["start"] > at, between(at, s["start"])).otherwise(""), F.lit(mark)))).otherwise(F.array().cast("array<string>"))

    kept = _folded(F.col("__all"), F.lit(0).cast("long"), "array<string>", step)
    end, size = F.array_max(F.transform("__all", lambda s: s["stop"])), F.length("__text").cast("long")
    done = F.concat(F.array_join(kept, ""), F.when(size > end, between(end, size)).otherwise(""))
    return found.withColumn(text_col, F.when(F.size("__all") > 0, done).otherwise(F.col(text_col))).select(*df.columns)
