"""Benchmark decontamination by spaced seeds.

A seed is a fixed mask over consecutive tokens whose zeros are not looked at, so
a hit survives a changed word under a zero. The seed hashes of the documents
are joined with those of the test items; around each hit the two token
sequences are laid on each other without gaps, and the longest region in
which at least `identity` of the tokens agree decides. Every passage of 12 to
30 tokens with up to a fifth of its inner tokens changed meets a mask (a test
enumerates them). Items of fewer than `least` tokens must lie in the document as a whole;
their seeds are as many pieces as changes are allowed and one more, one of which is unchanged.

One pass over the documents finds possible hits by a Bloom filter of the items'
seed hashes, which has at most 64 MB and only spares the join work; hits and postings
meet in a join in which frequent hashes are split, and postings of one hash
come in lists of bounded length.

Tokens are lower-cased and split at blanks and ASCII punctuation. Defined results:
null and blank texts, of items or documents, overlap nothing; items under six
tokens must occur whole and unchanged; repeated rows and equal items are each reported;
an empty table on either side gives an empty result; columns besides id and
text are ignored, whatever their names.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import binary_list, materialize, salted_join, thrifty

#: Fixed seeds of weight 6.
MASKS = ("111111", "1110111", "1101111", "1111011", "11011011", "11100111", "1101010011")
_PUNCTUATION = bytes(range(33, 48)) + bytes(range(58, 65)) + bytes(range(91, 97)) + bytes(range(123, 127))
_TABLE = bytes.maketrans(_PUNCTUATION, b" " * len(_PUNCTUATION))
FOUND = "doc_id long, item_id long, doc_start long, item_start long, n_tokens long, n_equal long"
#: Postings of one hash in one list, and tokens hashed at a time.
LISTED, PIECE = 1_000, 1 << 20


def tokens(text: bytes | None) -> list[bytes]:
    return (text or b"").decode("utf-8", "replace").lower().encode().translate(_TABLE).split()


def word_hashes(text: bytes | None) -> np.ndarray:
    words = tokens(text)
    return np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))


def places(mask: str) -> list[int]:
    return [i for i, c in enumerate(mask) if c == "1"]


def seed_hashes(words: np.ndarray, mask: str) -> np.ndarray:
    """The hash of the mask at each place of a token sequence."""
    at = places(mask)
    n = len(words) - at[-1]
    if n <= 0:
        return np.empty(0, np.uint64)
    h = np.full(n, xxhash.xxh64_intdigest(mask.encode()), np.uint64)
    for i in at:
        h = (h + words[i : i + n]) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(29)
    return h * np.uint64(0xBF58476D1CE4E5B9)


def item_seeds(words: np.ndarray, identity: float, least: int) -> list[tuple[str, np.ndarray, np.ndarray]]:
    """(mask, places, hashes) under which an item is posted."""
    n = len(words)
    if n >= least:
        return [(m, np.arange(len(h)), h) for m in MASKS for h in [seed_hashes(words, m)]]
    changes = int(n * (1 - identity) + 1e-9) if n >= 6 else 0
    size = n // (changes + 1)
    at = np.arange(changes + 1) * size
    return [("1" * size, at, seed_hashes(words, "1" * size)[at])] if n else []


def masks_for(lengths, least: int, identity: float) -> list[str]:
    """The masks that items of these numbers of tokens are posted under."""
    short = {n // (int(n * (1 - identity) + 1e-9) + 1) if n >= 6 else n for n in lengths if n < least}
    return [*(MASKS if any(n >= least for n in lengths) else ()), *("1" * size for size in sorted(short))]


class Filter:
    """A Bloom filter of seed hashes with two probes, of 8 to 64 MB by the number of hashes: small ones pass one hash in millions."""

    def __init__(self, n: int):
        self.bits = min(29, max(26, (64 * max(1, n)).bit_length()))
        self.table = np.zeros(1 << self.bits - 3, np.uint8)

    def _probes(self, hashes: np.ndarray):
        for shift in (64 - self.bits, 5):
            at = hashes >> np.uint64(shift) & np.uint64((1 << self.bits) - 1)
            yield (at >> np.uint64(3)).astype(np.int64), np.uint8(1) << (at & np.uint64(7)).astype(np.uint8)

    def add(self, hashes: np.ndarray) -> None:
        for at, bit in self._probes(hashes):
            np.bitwise_or.at(self.table, at, bit)

    def holds(self, hashes: np.ndarray) -> np.ndarray:
        """The places of hashes that may be in the filter."""
        (at, bit), (at2, bit2) = self._probes(hashes)
        first = np.flatnonzero(self.table[at] & bit)
        return first[(self.table[at2[first]] & bit2[first]) > 0]


def longest_region(equal: np.ndarray, identity: float) -> tuple[int, int, int] | None:
    """(start, size, equal tokens) of the longest stretch that begins and ends in equal tokens and has at least that share of them."""
    at = np.flatnonzero(equal)
    if not len(at):
        return None
    n = np.arange(1, len(at) + 1)
    lead = n - identity * (at + 1)
    before = (n - 1) - identity * at
    low = np.minimum.accumulate(before)  # of all starts so far
    best = None
    for j in range(len(at) - 1, -1, -1):
        if best and at[j] + 1 <= best[1]:
            break
        if lead[j] >= low[j] - 1e-9:
            i = int(np.argmax(before[: j + 1] <= lead[j] + 1e-9))
            size = int(at[j] - at[i] + 1)
            if not best or size > best[1]:
                best = (int(at[i]), size, j - i + 1)
    return best


def posted(items: DataFrame, identity: float, least: int) -> DataFrame:
    """(hash, item_no, at) of every seed of every item."""

    def run(batches):
        for b in batches:
            for no, words in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                for _, at, hashes in item_seeds(np.frombuffer(words, np.uint64), identity, least):
                    yield pa.RecordBatch.from_arrays([pa.array(hashes.view(np.int64)), pa.array(np.full(len(at), no)), pa.array(at.astype(np.int32))], ["hash", "item_no", "at"])

    return items.select("item_no", "item_words").mapInArrow(thrifty(run), "hash long, item_no long, at int")


def filter_of(hashes: DataFrame, n: int) -> Filter:
    """The filter of a column of hashes, made in a few tasks and joined by or."""

    def run(batches):
        own = Filter(n)
        for b in batches:
            own.add(b.column(0).to_numpy().view(np.uint64))
        yield pa.RecordBatch.from_arrays([pa.array([own.table.tobytes()], pa.large_binary())], ["data"])

    whole = Filter(n)
    for r in hashes.repartition(4).mapInArrow(thrifty(run), "data binary").toLocalIterator():  # four rows of at most 64 MB
        whole.table |= np.frombuffer(r["data"], np.uint8)
    return whole


def possible_hits(rows: DataFrame, held, masks: list[str]) -> DataFrame:
    """(doc_key, doc_id, k1, k2, doc_words, hits) of the rows (doc_id, text, k1, k2) in which some seed may be an item's."""

    def search(words: np.ndarray, ends: np.ndarray):
        """(document, place, hash) of possible hits, of several documents' words in a row."""
        docs, at, found = [], [], []
        for mask in masks:
            h = seed_hashes(words, mask)
            place = held.value.holds(h)
            doc = np.searchsorted(ends, place, side="right")
            inside = place + len(mask) <= ends[doc] if len(place) else place.astype(bool)
            docs.append(doc[inside])
            at.append(place[inside])
            found.append(h[place[inside]])
        return (np.concatenate(x) for x in (docs, at, found))

    def run(batches):
        from pyspark import TaskContext

        key = TaskContext.get().partitionId() << 33
        for b in batches:
            ids, texts, k1, k2 = b.column(0).to_pylist(), binary_list(b.column(1)), b.column(2).to_pylist(), b.column(3).to_pylist()
            group, size = [], 0
            for i, text in enumerate(texts):
                group.append((i, word_hashes(text)))
                size += len(group[-1][1])
                if size < PIECE and i < len(texts) - 1:
                    continue
                lengths = np.array([len(w) for _, w in group])
                ends = np.cumsum(lengths)
                doc, at, found = search(np.concatenate([w for _, w in group]), ends)
                out = [[] for _ in range(6)]
                for d in np.unique(doc).tolist():
                    own = doc == d
                    no, words = group[d]
                    hits = [{"hash": h, "pos": p} for h, p in zip(found[own].view(np.int64).tolist(), (at[own] - (ends[d] - lengths[d])).tolist())]
                    for column, value in zip(out, (key, ids[no], k1[no], k2[no], words.tobytes(), hits)):
                        column.append(value)
                    key += 1
                if out[0]:
                    kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.list_(pa.struct([("hash", pa.int64()), ("pos", pa.int32())])))
                    yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(out, kinds)], ["doc_key", "doc_id", "k1", "k2", "doc_words", "hits"])
                group, size = [], 0

    return rows.mapInArrow(thrifty(run), "doc_key long, doc_id long, k1 long, k2 long, doc_words binary, hits array<struct<hash: long, pos: int>>")


def overlaps(docs: DataFrame, benchmark: DataFrame, id_col: str, text_col: str, item_id_col: str, item_text_col: str, identity: float, least: int) -> DataFrame:
    """FOUND rows with the two hashes of the document's text (k1, k2): of each document and item the longest verified overlap."""
    spark = docs.sparkSession

    def hashed(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([word_hashes(t).tobytes() for t in binary_list(b.column(2))], pa.binary())], ["item_no", "item_id", "item_words"])

    named = benchmark.select(F.monotonically_increasing_id().alias("item_no"), F.col(item_id_col).cast("long").alias("item_id"), F.col(item_text_col).alias("text")).where(F.col("text").isNotNull())
    items = materialize(named.mapInArrow(thrifty(hashed), "item_no long, item_id long, item_words binary").where(F.octet_length("item_words") > 0), "items")
    postings = materialize(posted(items, identity, least), "postings")
    n = postings.count()
    text = F.col(text_col)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), text.alias("text"), *text_keys(text))
    held = spark.sparkContext.broadcast(filter_of(postings.select("hash"), n))
    words = F.least(F.octet_length("item_words") / 8, F.lit(least)).cast("int")
    lengths = [r["n"] for r in items.select(words.alias("n")).distinct().collect()]  # at most `least` of them
    hit = materialize(possible_hits(rows, held, masks_for(lengths, least, identity)), "hits") if n else spark.createDataFrame([], "doc_key long, doc_id long, k1 long, k2 long, doc_words binary, hits array<struct<hash: long, pos: int>>")
    seeds = hit.select("doc_key", F.explode("hits").alias("h")).select("doc_key", "h.hash", "h.pos")
    lists = postings.groupBy("hash", F.pmod(F.xxhash64("item_no", "at"), F.lit(max(1, n // LISTED))).alias("list")).agg(F.collect_list(F.struct("item_no", "at")).alias("posted")).drop("list") if n > LISTED else postings.groupBy("hash").agg(F.collect_list(F.struct("item_no", "at")).alias("posted"))
    met = salted_join(seeds, lists, "hash", "doc_key", hit.agg(F.sum(F.size("hits"))).first()[0] or 0)
    laid = materialize(met.select("doc_key", "pos", F.explode("posted").alias("p")).select("doc_key", "p.item_no", (F.col("pos") - F.col("p.at")).alias("shift")).distinct(), "laid")
    m = laid.count()
    with_items = salted_join(laid, items, "item_no", "doc_key", m)
    both = salted_join(with_items, hit.drop("hits"), "doc_key", "item_no", m)
    start, item_start = F.greatest("shift", F.lit(0)), F.greatest(-F.col("shift"), F.lit(0))
    size = F.least(F.octet_length("doc_words") / 8 - start, F.octet_length("item_words") / 8 - item_start).cast("int")
    cut = lambda c, at: F.substring(c, at * 8 + 1, size * 8)
    slices = both.select("doc_key", "item_no", "doc_id", "item_id", "k1", "k2", start.cast("long").alias("start"), item_start.cast("long").alias("item_start"), (F.octet_length("item_words") / 8).cast("long").alias("n_item"), cut("doc_words", start).alias("d"), cut("item_words", item_start).alias("i"))

    def verified(batches):
        for b in batches:
            out = [[] for _ in range(4)]
            for row, (n_item, d, i) in enumerate(zip(b.column(8).to_pylist(), b.column(9).to_pylist(), b.column(10).to_pylist())):
                region = longest_region(np.frombuffer(d, np.uint64) == np.frombuffer(i, np.uint64), identity)
                if region and region[1] >= min(least, n_item):
                    for column, value in zip(out, (row, *region)):
                        column.append(value)
            if out[0]:
                kept = b.take(pa.array(out[0]))
                at = pa.array(out[1], pa.int64())
                yield pa.RecordBatch.from_arrays([*kept.columns[:6], pa.compute.add(kept.column(6), at), pa.compute.add(kept.column(7), at), pa.array(out[2], pa.int64()), pa.array(out[3], pa.int64())], ["doc_key", "item_no", "doc_id", "item_id", "k1", "k2", "doc_start", "item_start", "n_tokens", "n_equal"])

    regions = slices.mapInArrow(thrifty(verified), f"doc_key long, item_no long, doc_id long, item_id long, k1 long, k2 long, {', '.join(FOUND.split(', ')[2:])}")
    best = F.struct("n_tokens", "n_equal", -F.col("doc_start"), "doc_id", "item_id", "k1", "k2", "doc_start", "item_start")
    longest = regions.groupBy("doc_key", "item_no").agg(F.max(best).alias("b"))
    return longest.select(*[f"b.{c.split()[0]}" for c in FOUND.split(", ")], "b.k1", "b.k2")


def text_keys(text) -> list:
    """128 bits that tell texts apart: what is found of a text holds for all rows with it, whatever their ids."""
    return [F.xxhash64(text).alias("k1"), F.xxhash64(text, F.lit(1)).alias("k2")]


def contaminated(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_id_col: str = "item_id", item_text_col: str = "text", identity: float = 0.8, least: int = 12) -> DataFrame:
    """Verified overlaps: doc_id, item_id, doc_start, item_start, n_tokens, n_equal (positions in tokens)."""
    return overlaps(docs, benchmark, id_col, text_col, item_id_col, item_text_col, identity, least).drop("k1", "k2")


def decontaminate(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_id_col: str = "item_id", item_text_col: str = "text", identity: float = 0.8, least: int = 12, told: int = 500_000) -> DataFrame:
    """The documents without a verified overlap, judged by their text, so rows without id too. Up to `told` hit texts (16 bytes each) are told to all tasks, and no document moves."""
    hit = materialize(overlaps(docs, benchmark, id_col, text_col, item_id_col, item_text_col, identity, least).select(F.col("k1").alias("__k1"), F.col("k2").alias("__k2")).distinct(), "contaminated")
    few = F.broadcast(hit) if hit.count() <= told else hit
    k1, k2 = text_keys(F.col(text_col))
    return docs.join(few, (k1 == F.col("__k1")) & (k2 == F.col("__k2")), "left_anti")
