"""Word language model by a hierarchical Pitman-Yor process, trained and applied without moving a text twice.

Every token is predicted from the word before it. Each word opens a restaurant
for its successors; all these context restaurants share the root as parent, and
the root draws from a uniform base over the known words and one unknown. The
seating is sampled by Gibbs, a dish of a restaurant at a time: all customers of
the dish are seated anew at once, that is, the number of their tables is drawn from its
conditional given all other dishes, which is all that predictions depend on.
Up to `EXACT` customers the conditional is exact, by generalised Stirling numbers;
beyond, their saddle-point approximation gives its mode and spread. There is no cap on
tables or customers. Dishes in different parts are drawn side by side, given the
totals of the round before. After `burn` rounds, `samples` rounds are kept, and
predictive probabilities are averaged over them in double precision.

What grows with the corpus stays distributed and in files of bounded size. A
chunk of documents sends its distinct words to shards by hash, which number the
words, and then its distinct (word before, word) pairs, as numbers, to parts by
the word before; the pairs of a very frequent word are dealt by both words. A
part merges counts and keeps for each chunk which of its rows it asked for.
In a round a part sends the shards two sums a word (tables of its restaurant,
tables that serve it) and gets the totals back; answers to a chunk are customers and tables,
small integers from which it computes its probabilities. Chunks, parts and
shards grow with the cube root of the corpus, so that the messages between them stay few.

Defined results: a null text counts as empty and still has its end token;
repeated rows are each scored and learned from; a null id falls in the fold of
the empty text; with nothing to learn from, all words are equally unknown; an
empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import pickle
import uuid

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import binary_list, fold, fresh_path
from .warc import file_system

#: dest: the chunk, shard or part that a row is for; source: who sends it.
ROWS = "dest long, source long, tag string, path string, data binary"
NAMES = [c.split()[0] for c in ROWS.split(", ")]
#: Discounts and strengths of context restaurants and of the root.
DISCOUNT, STRENGTH, ROOT_DISCOUNT, ROOT_STRENGTH = 0.8, 1.0, 0.5, 1.0
EXACT = 64
#: Up to so many customers the weights of all numbers of tables fit in double precision without logarithms.
PLAIN = 16


def pack(*arrays) -> bytes:
    return zstandard.compress(pickle.dumps(arrays, protocol=5), 1)


def unpack(data: bytes) -> tuple:
    return pickle.loads(zstandard.decompress(bytes(data)))


def small(x: np.ndarray) -> np.ndarray:
    """The same whole numbers (none negative) in the least bytes each."""
    top = int(x.max()) if len(x) else 0
    return x.astype(np.uint8 if top < 256 else np.uint16 if top < 65536 else np.uint32 if top < 1 << 32 else np.uint64)


def planes(x: np.ndarray) -> np.ndarray:
    """small(x) by byte, so that the even bytes compress well."""
    x = np.ascontiguousarray(small(x))
    return np.ascontiguousarray(x.view(np.uint8).reshape(len(x), x.itemsize).T)


def joined(x: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(x.T).view({1: np.uint8, 2: np.uint16, 4: np.uint32, 8: np.uint64}[len(x)]).ravel().astype(np.int64)


def steps(x: np.ndarray) -> np.ndarray:
    """Ascending numbers as differences."""
    return planes(np.diff(x, prepend=0))


def summed(x: np.ndarray) -> np.ndarray:
    return np.cumsum(joined(x))


def put(folder: str, *arrays) -> str:
    """A file of its own in the shared storage; what a lost or repeated task wrote is never read, as only finished rows name files."""
    shared, place = file_system(folder)
    shared.create_dir(place, recursive=True)
    name = uuid.uuid4().hex
    with shared.open_output_stream(f"{place}/{name}", compression=None) as out:
        out.write(pack(*arrays))
    return f"{folder}/{name}"


def get(path: str) -> tuple:
    shared, place = file_system(path)
    with shared.open_input_stream(place, compression=None) as stream:
        return unpack(stream.read())


def rows_of(found) -> pd.DataFrame:
    return pd.DataFrame(found, columns=NAMES, dtype=object)


# -- seating ------------------------------------------------


def log_stirling(discount: float, most: int = EXACT) -> np.ndarray:
    """log S[c, t]: the weight of all ways to seat c customers at t tables, where a table of n has the weight (1 - d)(2 - d)...(n - 1 - d)."""
    out = np.full((most + 1, most + 1), -np.inf)
    out[0, 0] = 0.0
    for c in range(most):
        t = np.arange(1, most + 1)
        with np.errstate(divide="ignore"):
            stay = np.where(c - discount * t > 0, np.log(np.maximum(c - discount * t, 1e-300)), -np.inf) + out[c, 1:]
        out[c + 1, 1:] = np.logaddexp(out[c, :-1], stay)
    return out


def saddle(s: np.ndarray, c, discount: float) -> tuple[np.ndarray, np.ndarray]:
    """(t, log phi) at z = 1 - exp(-s): phi(z) = (1 - (1 - z)^d) / d generates the weights, S[c, t] / c! being the coefficient of z^c in phi(z)^t / t!, and t is the number of tables for which z is the saddle point."""
    phi, z = -np.expm1(-discount * s) / discount, -np.expm1(-s)
    return c * phi / (z * np.exp(s * (1 - discount))), np.log(phi)


def bisected(shape, falls) -> np.ndarray:
    """The s at which falls(s) turns true; it is true from there on."""
    low, high = np.full(shape, 1e-9), np.full(shape, 200.0)
    for _ in range(50):
        middle = (low + high) / 2
        beyond = falls(middle)
        high, low = np.where(beyond, middle, high), np.where(beyond, low, middle)
    return low


def likely_tables(c: np.ndarray, first: np.ndarray, more: np.ndarray, discount: float) -> tuple[np.ndarray, np.ndarray]:
    """Mode and spread of the number of tables of many customers, p(t) ~ S[c, t] (first)(first + more)...(first + (t - 1) more), where S[c, t + 1] / S[c, t] is phi / t at the saddle point."""

    def at(s):
        t, phi = saddle(s, c, discount)
        return t, np.log(first + more * t) + phi - np.log(t)

    s = bisected(len(c), lambda s: at(s)[1] > 0)
    (t_up, h_up), (t_down, h_down) = at(s * 1.001), at(s * 0.999)
    slope = (h_up - h_down) / np.where(t_up == t_down, -1.0, t_up - t_down)
    return at(s)[0], np.sqrt(1 / np.maximum(-slope, 1e-12))


def few_tables(c: np.ndarray, first: np.ndarray, more: np.ndarray, discount: float, rng, most: int = 48) -> np.ndarray:
    """Draws where few tables are likely: the law of 1 to `most` tables from these ratios. Saddle points depend on the customers alone, so each number of customers finds them once."""
    own, which = np.unique(c, return_inverse=True)
    t = np.arange(1, most)[None, :] + np.zeros((len(own), 1))
    s = bisected(t.shape, lambda s: saddle(s, own[:, None], discount)[0] < t)
    fixed = saddle(s, own[:, None], discount)[1] - np.log(t)
    ratio = np.log(first[:, None] + more[:, None] * t[:1]) + fixed[which]
    weight = np.concatenate([np.zeros((len(c), 1)), ratio.cumsum(axis=1)], axis=1)
    weight = np.exp(weight - weight.max(axis=1, keepdims=True)).cumsum(axis=1)
    return 1 + (weight < (rng.random(len(c)) * weight[:, -1])[:, None]).sum(axis=1)


class Tables:
    """Draws the number of tables of each dish from its conditional."""

    def __init__(self, discount: float):
        self.discount, self.logs = discount, log_stirling(discount)

    def draw(self, customers: np.ndarray, first: np.ndarray, more: np.ndarray, rng, piece: int = 1 << 20) -> np.ndarray:
        """first: weight of a dish's first table; more: what each further one adds to the weight of the next."""
        out = np.minimum(customers, 1).astype(np.int64)
        order = np.argsort(customers, kind="stable")
        cut = np.searchsorted(customers[order], np.arange(2, EXACT + 2))
        for c in range(2, EXACT + 1):
            rows = order[cut[c - 2] : cut[c - 1]]
            for at in range(0, len(rows), max(1, piece // c)):
                own = rows[at : at + max(1, piece // c)]
                if c <= PLAIN:  # weights relative to one table
                    weight = np.ones((len(own), c))
                    np.multiply(first[own][:, None] + more[own][:, None] * np.arange(1, c), np.exp(np.diff(self.logs[c, 1 : c + 1])), out=weight[:, 1:])
                    weight = weight.cumprod(axis=1).cumsum(axis=1)
                else:
                    weight = np.log(first[own][:, None] + more[own][:, None] * np.arange(c)).cumsum(axis=1) + self.logs[c, 1 : c + 1]
                    weight = np.exp(weight - weight.max(axis=1, keepdims=True)).cumsum(axis=1)
                out[own] = 1 + (weight < (rng.random(len(own)) * weight[:, -1])[:, None]).sum(axis=1)
        rows = order[cut[-1] :]
        if len(rows):
            c = customers[rows].astype(np.float64)
            mode, spread = likely_tables(c, first[rows], more[rows], self.discount)
            out[rows] = np.clip(np.rint(mode + 0.5 + spread * rng.standard_normal(len(rows))), 1, c)
            few = np.flatnonzero(mode < 16)
            if len(few):
                out[rows[few]] = few_tables(c[few], first[rows][few], more[rows][few], self.discount, rng)
        return out


def sweep(tables: Tables, customers, own, context, word, totals, p, rng, turns: int = 1):
    """Gibbs over the dishes of one part. own: tables now; totals: tables of each context restaurant, all parts; p: root probability of each word."""
    live = np.flatnonzero(customers > 1)
    c, v, w = customers[live], context[live], word[live]
    first_p, here = p[w], np.bincount(context, own, len(totals))
    now = own.copy()
    level = totals.astype(np.float64)
    for _ in range(turns):
        others = np.maximum(level[v] - now[live], 0)
        now[live] = tables.draw(c, (STRENGTH + DISCOUNT * others) * first_p, DISCOUNT * first_p, rng)
        level = totals + np.bincount(context, now, len(totals)) - here
    return now


class Root:
    """The root's part of a state: customers and tables of all words, number of known words."""

    def __init__(self, customers: float, tables: float, words: int):
        self.customers, self.tables, self.words = customers, tables, words

    def p(self, customers: np.ndarray, tables: np.ndarray) -> np.ndarray:
        return (np.maximum(customers - ROOT_DISCOUNT * tables, 0) + (ROOT_STRENGTH + ROOT_DISCOUNT * self.tables) / (self.words + 1)) / (ROOT_STRENGTH + self.customers)


def predictive(c, t, context_customers, context_tables, p):
    """Probability of a word after a context, from the customers and tables of the pair, of the context, and the word's root probability."""
    return (np.maximum(c - DISCOUNT * t, 0) + (STRENGTH + DISCOUNT * context_tables) * p) / (STRENGTH + context_customers)


# -- chunks, shards, parts ------------------------------------------------


class _Numbers(dict):
    def __missing__(self, word):
        self[word] = n = len(self)
        return n


class Plan:
    """Sizes of a run: how many shards and parts, and where each word's numbers begin."""

    def __init__(self, size: int, folder: str, chunk_bytes: int, part_bytes: int, shard_bytes: int, seed: int):
        grow = max(1.0, (size / (1 << 30)) ** (1 / 3))
        self.folder, self.seed = folder, seed
        self.chunk_bytes = int(chunk_bytes * grow)
        self.parts, self.shards = max(4, -(-size // int(part_bytes * grow))), max(4, -(-size // int(shard_bytes * grow)))
        self.hot_count = max(10_000, size // (48 * self.parts))
        self.offsets, self.words, self.known, self.tokens, self.hot = np.zeros(self.shards + 1, np.int64), 0, 0, 0, np.empty(0, np.int64)

    def part_of(self, v: np.ndarray, w: np.ndarray) -> np.ndarray:
        """By the word before; the pairs of a frequent one are dealt by both words."""
        part = v * self.parts // max(1, self.words)
        frequent = np.isin(v, self.hot)
        mixed = (v.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) ^ w.astype(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F)) >> np.uint64(33)
        return np.where(frequent, (mixed % np.uint64(self.parts)).astype(np.int64), part)


class Chunk:
    """Documents of one chunk as a stream of word numbers; number 0 ends each text and stands before its first word."""

    def __init__(self):
        self.numbers = _Numbers({b"": 0})
        self.streams, self.ids, self.held, self.size = [], [], [], 0

    def add(self, doc_id, held: bool, text: bytes | None) -> None:
        words = (text or b"").lower().split()
        self.streams.append(np.fromiter(map(self.numbers.__getitem__, words), np.int32, len(words)))
        self.ids.append(doc_id)
        self.held.append(held)
        self.size += len(text or b"") + 40

    def finish(self, plan: Plan, number: int):
        """The row that names the chunk's file, and its words for each shard."""
        hashes = np.fromiter(map(xxhash.xxh64_intdigest, self.numbers), np.uint64, len(self.numbers))
        self.numbers.clear()
        order = np.argsort(hashes)
        place = np.empty(len(order), np.int64)
        place[order] = np.arange(len(order))
        lengths = np.array([len(s) + 1 for s in self.streams])
        end = np.zeros(1, np.int32)
        spoken = np.concatenate([x for s in self.streams for x in (s, end)])
        held = np.array(self.held)
        learned = np.bincount(place[spoken[~np.repeat(held, lengths)]], minlength=len(order))
        null = np.array([i is None for i in self.ids])
        ids = np.array([0 if i is None else i for i in self.ids], np.int64)
        path = put(f"{plan.folder}/chunk", ids, null, held, lengths, planes(spoken), planes(place))
        yield number, number, "own", path, None
        shard = ((hashes[order] >> np.uint64(32)) * np.uint64(plan.shards)) >> np.uint64(32)
        cut = np.searchsorted(shard, np.arange(plan.shards + 1))
        for s in range(plan.shards):
            if cut[s + 1] > cut[s]:
                own = slice(cut[s], cut[s + 1])
                yield s, number, "words", None, pack(hashes[order][own], small(learned[own]))


def chunk_documents(df: DataFrame, id_col: str, text_col: str, folds: int, held_fold: int, plan: Plan) -> DataFrame:
    rows = df.select(F.col(id_col).cast("long").alias("id"), (fold(F.col(id_col), folds) == held_fold).alias("held"), F.col(text_col).alias("text"))

    def emit(chunk: Chunk, number: int):
        yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*chunk.finish(plan, number)), (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.binary()))], NAMES)

    def run(batches):
        from pyspark import TaskContext

        number, chunk = TaskContext.get().partitionId() << 24, Chunk()
        for b in batches:
            for doc_id, held, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), binary_list(b.column(2))):
                chunk.add(doc_id, held, text)
                if chunk.size > plan.chunk_bytes:
                    yield from emit(chunk, number)
                    number, chunk = number + 1, Chunk()
        if chunk.ids:
            yield from emit(chunk, number)

    return rows.mapInArrow(run, ROWS)


def number_words(pdf: pd.DataFrame, plan: Plan) -> pd.DataFrame:
    """A shard: its words in order of their hashes with training counts, and to each chunk the places of its words."""
    shard, sent = int(pdf["dest"].iloc[0]), [unpack(x) for x in pdf["data"]]
    words = np.unique(np.concatenate([h for h, _ in sent]))
    places = [np.searchsorted(words, h) for h, _ in sent]
    counts = np.zeros(len(words), np.int64)
    for at, (_, n) in zip(places, sent):
        counts[at] += n.astype(np.int64)
    chunks = pdf["source"].tolist()
    path = put(f"{plan.folder}/shard", counts, {c: steps(at) for c, at in zip(chunks, places)})
    hot = np.flatnonzero(counts > plan.hot_count)
    out = [(shard, shard, "shard", path, pack(np.array([len(words), (counts > 0).sum(), counts.sum()]), hot))]
    return rows_of(out + [(c, shard, "ids", None, pack(steps(at))) for c, at in zip(chunks, places)])


class Pairs:
    """The distinct pairs of a chunk in the order in which parts are asked for them."""

    def __init__(self, own: tuple, sent: pd.DataFrame, plan: Plan, of_tokens: bool):
        """With of_tokens, the pair of each token; else the number of times that each pair is learned from, for which a plain sort is enough."""
        _, _, held, lengths, spoken, place = own
        sent = sent.sort_values("source")
        self.ids = np.concatenate([summed(unpack(x)[0]) + plan.offsets[s] for s, x in zip(sent["source"], sent["data"])])
        place = joined(place)
        self.stream = place[joined(spoken)]
        keys = np.concatenate([place[:1], self.stream[:-1]]) << 32 | self.stream  # every text ends with number 0
        if of_tokens:
            keys, of_token = np.unique(keys, return_inverse=True)
        else:
            keys = np.sort(keys << 1 | np.repeat(held, lengths))
            learned, keys = (keys & 1) == 0, keys >> 1
            first = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
            keys, counts = keys[first], np.add.reduceat(learned.astype(np.int64), first)
        v, w = keys >> 32, keys & 0xFFFFFFFF
        part = plan.part_of(self.ids[v], self.ids[w])
        order = np.argsort(part, kind="stable")
        self.v, self.w, self.part = v[order], w[order], part[order]
        if of_tokens:
            turn = np.empty(len(order), np.int64)
            turn[order] = np.arange(len(order))
            self.of_token = turn[of_token]
        else:
            self.counts = counts[order]


def ask_parts(pdf: pd.DataFrame, plan: Plan) -> pd.DataFrame:
    """A chunk: its pairs as word numbers, with counts, to each part."""
    own = pdf[pdf["tag"] == "own"].iloc[0]
    pairs = Pairs(get(own["path"]), pdf[pdf["tag"] == "ids"], plan, False)
    parts = np.unique(pairs.part)
    cut = np.searchsorted(pairs.part, np.append(parts, plan.parts))
    out = []
    for n, p in enumerate(parts):
        at = slice(cut[n], cut[n + 1])
        v = pairs.v[at]
        first = np.flatnonzero(np.concatenate([[True], v[1:] != v[:-1]]))
        out.append((p, own["dest"], "pairs", None, pack(steps(pairs.ids[v[first]]), small(np.diff(np.append(first, len(v)))), planes(pairs.ids[pairs.w[at]]), small(pairs.counts[at]))))
    return rows_of(out)


def to_shards(part: int, words: np.ndarray, context_tables: np.ndarray, served: np.ndarray, plan: Plan) -> list[tuple]:
    """What a part adds to the totals of its words, by shard."""
    cut = np.searchsorted(words, plan.offsets)
    return [(s, part, "sums", None, pack(steps(words[cut[s] : cut[s + 1]] - plan.offsets[s]), small(context_tables[cut[s] : cut[s + 1]]), small(served[cut[s] : cut[s + 1]]))) for s in range(plan.shards) if cut[s + 1] > cut[s]]


def merge_pairs(pdf: pd.DataFrame, plan: Plan) -> pd.DataFrame:
    """A part: counts of its pairs by word before and word, and for each chunk the rows it asked for. Every dish begins with one table."""
    part, sent = int(pdf["dest"].iloc[0]), []
    for data in pdf["data"]:
        v, each, w, n = unpack(data)
        sent.append((summed(v), each, joined(w), n))
    before = np.unique(np.concatenate([v for v, *_ in sent]))
    bits = max(1, int(plan.words).bit_length())
    keys = [np.repeat(np.searchsorted(before, v) << bits, each) | w for v, each, w, _ in sent]
    every = np.unique(np.concatenate(keys))
    asked = [np.searchsorted(every, k) for k in keys]
    counts = np.zeros(len(every), np.int64)
    for at, (*_, n) in zip(asked, sent):
        counts[at] += n.astype(np.int64)
    v, w = before[every >> bits], every & (1 << bits) - 1
    words = np.unique(np.concatenate([before, w]))
    context, word = np.searchsorted(words, v), np.searchsorted(words, w)
    table = put(f"{plan.folder}/part", steps(words), planes(context), planes(word), small(counts))
    index = put(f"{plan.folder}/part", {c: steps(at) for c, at in zip(pdf["source"], asked)})
    one = np.minimum(counts, 1)
    state = put(f"{plan.folder}/part", small(one))
    return rows_of([(part, part, "part", table, pack(index, state)), *to_shards(part, words, np.bincount(context, one, len(words)), np.bincount(word, one, len(words)), plan)])


def shard_round(pdf: pd.DataFrame, plan: Plan, root: Root, turn: int) -> pd.DataFrame:
    """A shard: totals of its words over all parts, tables of the root drawn, and to each part the totals of its words."""
    own = pdf[pdf["tag"] == "shard"].iloc[0]
    shard, (counts, _) = int(own["dest"]), get(own["path"])
    tables, customers = np.zeros(len(counts), np.int64), np.zeros(len(counts), np.int64)
    sent = pdf[pdf["tag"] == "sums"].sort_values("source")
    parts = []
    for source, data in zip(sent["source"], sent["data"]):
        at, t, c = unpack(data)
        at = summed(at)
        tables[at] += t.astype(np.int64)
        customers[at] += c.astype(np.int64)
        parts.append((source, at))
    rng = np.random.default_rng([plan.seed, 1, turn, shard])
    serving = np.minimum(customers, 1)
    share = 1 / (root.words + 1)
    for _ in range(2):
        others = np.maximum(root.tables - serving, 0)
        serving = Tables(ROOT_DISCOUNT).draw(customers, (ROOT_STRENGTH + ROOT_DISCOUNT * others) * share, np.full(len(customers), ROOT_DISCOUNT * share), rng)
    state = put(f"{plan.folder}/shard", small(tables), small(customers), small(serving))
    out = [(shard, shard, "state", state, pack(np.array([customers.sum(), serving.sum(), tables.sum()])))]
    return rows_of(out + [(p, shard, "totals", None, pack(small(tables[at]), small(customers[at]), small(serving[at]))) for p, at in parts])


def part_round(pdf: pd.DataFrame, plan: Plan, root: Root, turn: int, turns: int) -> pd.DataFrame:
    """A part: its dishes seated anew given the totals, and what they add to them now."""
    own = pdf[pdf["tag"] == "part"].iloc[0]
    part, (index, state) = int(own["dest"]), unpack(own["data"])
    words, context, word, counts = get(own["path"])
    words, context, word, counts = summed(words), joined(context), joined(word), counts.astype(np.int64)
    now = get(state)[0].astype(np.int64)
    sent = pdf[pdf["tag"] == "totals"].sort_values("source")
    totals, customers, serving = (np.concatenate(x).astype(np.int64) for x in zip(*(unpack(d) for d in sent["data"])))
    rng = np.random.default_rng([plan.seed, 2, turn, part])
    now = sweep(Tables(DISCOUNT), counts, now, context, word, totals, root.p(customers, serving), rng, turns)
    state = put(f"{plan.folder}/part", small(now))
    return rows_of([(part, part, "part", own["path"], pack(index, state)), *to_shards(part, words, np.bincount(context, now, len(words)), np.bincount(word, now, len(words)), plan)])


def part_answers(pdf: pd.DataFrame, plan: Plan) -> pd.DataFrame:
    """To each chunk: customers, and tables in each sample, of the pairs it asked for."""
    part, out = int(pdf["dest"].iloc[0]), []
    counts = get(pdf["path"].iloc[0])[3]
    named = [unpack(d) for d in pdf.sort_values("source")["data"]]
    tables = [get(state)[0] for _, state in named]
    for chunk, at in get(named[0][0])[0].items():
        at = summed(at)
        out.append((chunk, part, "tables", None, pack(small(counts[at]), *[small(t[at]) for t in tables])))
    return rows_of(out)


def shard_answers(pdf: pd.DataFrame, plan: Plan) -> pd.DataFrame:
    """To each chunk: places and training counts of its words, and in each sample the tables of their restaurants, their customers and tables in the root."""
    shard, out = int(pdf["dest"].iloc[0]), []
    counts, asked = get(pdf[pdf["tag"] == "shard"]["path"].iloc[0])
    states = [get(p) for p in pdf[pdf["tag"] == "state"].sort_values("source")["path"]]
    for chunk, at in asked.items():
        place = summed(at)
        out.append((chunk, shard, "ids", None, pack(at, small(counts[place]), *[tuple(small(x[place]) for x in s) for s in states])))
    return rows_of(out)


RESULT = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double, perplexity double"


def score_chunk(pdf: pd.DataFrame, plan: Plan, roots: list[Root]) -> pd.DataFrame:
    own = get(pdf[pdf["tag"] == "own"]["path"].iloc[0])
    ids, null, held, lengths, _, _ = own
    sent = pdf[pdf["tag"] == "ids"].sort_values("source")
    pairs = Pairs(own, sent, plan, True)
    told = [unpack(x) for x in sent["data"]]
    counts = np.concatenate([t[1] for t in told]).astype(np.float64)
    answers = [unpack(x) for x in pdf[pdf["tag"] == "tables"].sort_values("source")["data"]]
    c = np.concatenate([a[0] for a in answers]).astype(np.float64)
    value = np.zeros(len(c))
    for s, root in enumerate(roots):
        tables, customers, serving = (np.concatenate([t[2 + s][i] for t in told]).astype(np.float64) for i in range(3))
        t = np.concatenate([a[1 + s] for a in answers]).astype(np.float64)
        value += predictive(c, t, counts[pairs.v], tables[pairs.v], root.p(customers, serving)[pairs.w]) / len(roots)
    value = np.log10(value)[pairs.of_token]
    n = counts[pairs.stream]
    first = np.cumsum(lengths) - lengths
    total = np.add.reduceat(value, first)
    base = np.add.reduceat(np.log10((n + 1) / (plan.tokens + plan.known + 1)), first)
    known = np.add.reduceat((n > 0).astype(np.int64), first)
    out = pd.DataFrame({"doc_id": pd.array(ids, "Int64"), "held_out": held, "n_tokens": lengths.astype(np.int64), "n_known": known, "train_tokens": plan.tokens, "base_score": base, "score": total, "perplexity": 10 ** np.minimum(300, -total / lengths)})
    out.loc[null, "doc_id"] = pd.NA
    return out


# -- the distributed whole ------------------------------------------------


def score(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", folds: int = 7, held_fold: int = 2, chunk_bytes: int = 12 << 20, part_bytes: int = 12 << 20, shard_bytes: int = 32 << 20, samples: int = 2, burn: int = 3, turns: int = 1, seed: int = 42, trace: list | None = None) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, perplexity of every row. trace: gets the tables of all context restaurants after each round."""
    spark = df.sparkSession
    size = df.agg(F.sum(F.octet_length(text_col))).first()[0] or 0
    root_path = fresh_path(spark, "hpylm")
    plan = Plan(size, root_path, chunk_bytes, part_bytes, shard_bytes, seed)

    def kept(rows: DataFrame, name: str) -> DataFrame:
        rows.write.parquet(f"{root_path}/{name}")
        return spark.read.schema(ROWS).parquet(f"{root_path}/{name}")

    def each(rows: DataFrame, tasks: int, work, *more) -> DataFrame:
        return rows.repartition(tasks, "dest").groupBy("dest").applyInPandas(lambda pdf: work(pdf, plan, *more), ROWS)

    first = kept(chunk_documents(df, id_col, text_col, folds, held_fold, plan), "first")
    own = first.where("tag = 'own'")
    chunks = max(1, own.count())
    words = kept(each(first.where("tag = 'words'"), plan.shards, number_words), "words")
    shards = words.where("tag = 'shard'")
    for r in sorted(shards.collect(), key=lambda r: r["dest"]):  # a row for each shard
        (n, known, tokens), hot = unpack(r["data"])
        plan.hot = np.append(plan.hot, plan.words + hot)
        plan.words, plan.known, plan.tokens = plan.words + int(n), plan.known + int(known), plan.tokens + int(tokens)
        plan.offsets[r["dest"] + 1 :] = plan.words
    asked = each(own.unionByName(words.where("tag = 'ids'")), chunks, ask_parts)
    parts = kept(each(asked, plan.parts, merge_pairs), "parts")
    own = own.select(*NAMES)
    root, kept_parts, kept_states, roots = Root(0.0, float(plan.known), plan.known), [], [], []
    for turn in range(burn + samples + 1):
        states = kept(each(shards.unionByName(parts.where("tag = 'sums'")), plan.shards, shard_round, root, turn), f"shards-{turn}")
        total = np.sum([unpack(r["data"])[0] for r in states.where("tag = 'state'").collect()] or [np.zeros(3)], axis=0)  # a row for each shard
        root = Root(float(total[0]), float(total[1]), plan.known)
        if trace is not None:
            trace.append(int(total[2]))
        if turn > burn:
            kept_parts.append(parts.where("tag = 'part'").withColumn("source", F.lit(turn).cast("long")))
            kept_states.append(states.where("tag = 'state'").withColumn("source", F.lit(turn).cast("long")))
            roots.append(root)
        if turn < burn + samples:
            parts = kept(each(parts.where("tag = 'part'").unionByName(states.where("tag = 'totals'")), plan.parts, part_round, root, turn, turns), f"parts-{turn}")
    every_part, every_state = kept_parts[0], shards
    for p in kept_parts[1:]:
        every_part = every_part.unionByName(p)
    for s in kept_states:
        every_state = every_state.unionByName(s)
    answers = each(every_part, plan.parts, part_answers).unionByName(each(every_state, plan.shards, shard_answers))
    return own.unionByName(answers).repartition(chunks, "dest").groupBy("dest").applyInPandas(lambda pdf: score_chunk(pdf, plan, roots), RESULT)
