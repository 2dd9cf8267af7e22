"""Near-copies: texts whose sets of word shingles have a Jaccard similarity of `similarity` or more.

SimHash fingerprints of the shingle sets are linked by multi-index hashing
(`simhash.links`), and every link is verified. An exact completion finds the
near-copies whose fingerprints lie further apart: of n shingles in one fixed
order, the first n - ceil(similarity * n) + 1 of two near-copies must share
one, so each text is filed under these and every pair of near-copies meets in a
file. Any order is right; here the shingles that a sample
of the texts repeats come last, so that a common line or license makes no file
unless a text consists of little else.

Two sets whose sizes differ by more than the similarity are no pair. A small
file yields all its other pairs, a larger one first the minimum spanning forest
of 64-bit SimHash fingerprints, cut at `reach`. The edges are verified by exact
Jaccard similarity, so no clean text is lost. Then every pair that met in a file
and is still in two components is verified too, in the task that holds the file, which
hands on the edges that join two components there: less than one a text, however many pairs it verifies. Before whole sets move, sketches
of a thirtieth of their size rule out pairs that differ too much, and only such: each pair is joined or refused by its own shingles, whatever its fingerprints. Files of more than `split_at`
texts are cut into blocks, and every two blocks form one file, so no task holds
more than about two blocks of it.

Defined results: texts with the same shingle set (null and blank ones too)
are copies; rows without id take no part and stay; repeated rows are copies of
each other; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import simhash
from .common import binary_list, connected_components, drop_path, materialize, salted_join, stored, thrifty

#: One text in so many is counted for the order of shingles; LISTED of its repeated shingles are known to all tasks. Both only shape the files.
SAMPLED, REPEATED, LISTED = 16, 3, 1 << 18
#: Files that a task works at together hold about so many bytes or are one.
HELD_BYTES = 32 << 20


def shingle_set(text: bytes | None, shingle: int = 5) -> np.ndarray:
    """Sorted distinct XXH64 values of the word shingles (fewer words: the whole sequence; none: empty)."""
    words = (text or b"").lower().split()
    if not words:
        return np.empty(0, np.uint64)
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    size = min(shingle, len(words))
    spans = zip(starts[: len(words) - size + 1].tolist(), ends[size - 1 :].tolist())
    return np.unique(np.fromiter((xxhash.xxh64_intdigest(joined[s:e], 42) for s, e in spans), np.uint64))


def set_id(hashes: np.ndarray) -> int:
    return int(np.uint64(xxhash.xxh64_intdigest(hashes.tobytes(), 7)).view(np.int64))


def fingerprint(hashes: np.ndarray) -> int:
    """SimHash: the majority of each bit."""
    ones = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 16_384):
        h = hashes[at : at + 16_384, None]
        ones += np.unpackbits(h.view(np.uint8).reshape(len(h), -1), axis=1, bitorder="little").sum(axis=0, dtype=np.uint32)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view(np.int64)[0])


def sketch(hashes: np.ndarray) -> bytes:
    """How many shingles fall in each of m buckets, odd or even: one bit each, m a power of two of at least twice the shingles.

    Two sets differ in at least as many shingles as their sketches differ in bits, so that a pair with too many differing bits is none."""
    m = max(64, 1 << (2 * len(hashes) - 1).bit_length()) if len(hashes) else 64
    odd = np.bincount((hashes & np.uint64(m - 1)).astype(np.int64), minlength=m) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").tobytes()


def folded(bits: np.ndarray) -> np.ndarray:
    """The sketches (rows of 64-bit words) for half as many buckets."""
    half = bits.shape[1] // 2
    if half:
        return bits[:, :half] ^ bits[:, half:]
    return (bits ^ bits >> np.uint64(32)) & np.uint64(0xFFFFFFFF)


def differing(x: np.ndarray, others: np.ndarray) -> np.ndarray:
    """Differing bits of one sketch and each of several of one size, larger ones folded."""
    x = x[None, :]
    while x.shape[1] > others.shape[1]:
        x = folded(x)
    while others.shape[1] > x.shape[1]:
        others = folded(others)
    return np.bitwise_count(x ^ others).sum(axis=1)


def possible(n, m, bits, similarity: float) -> np.ndarray:
    """Whether sets of n and m shingles whose sketches differ in so many bits may reach the similarity."""
    return bits <= (1 - similarity) / (1 + similarity) * (n + m) + 1e-6


def repeated(texts: DataFrame, shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """The shingles (ascending) that a sample of the texts repeats most, with their counts."""

    def run(batches):
        for b in batches:
            found = [shingle_set(t, shingle) for t in binary_list(b.column(0))]
            values, counts = np.unique(np.concatenate([np.empty(0, np.uint64), *found]), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(values.view(np.int64)), pa.array(counts.astype(np.int64))], ["hash", "n"])

    sample = texts.where(F.pmod(F.xxhash64("text"), F.lit(SAMPLED)) == 0).select("text")
    counts = sample.mapInArrow(thrifty(run), "hash long, n long").groupBy("hash").agg(F.sum("n").alias("n")).where(F.col("n") >= REPEATED)
    top = counts.orderBy(F.desc("n"), "hash").limit(LISTED).toArrow()
    hashes, n = top.column("hash").to_numpy().view(np.uint64), top.column("n").to_numpy()
    order = np.argsort(hashes)
    return hashes[order], n[order]


def prefix(hashes: np.ndarray, common: np.ndarray, counts: np.ndarray, similarity: float) -> np.ndarray:
    """The shingles a text is filed under: rare ones first, so many that two near-copies share one."""
    size = len(hashes) - math.ceil(similarity * len(hashes) - 1e-9) + 1 if len(hashes) else 0
    weight = np.zeros(len(hashes), np.int64)
    if len(common):
        at = np.minimum(np.searchsorted(common, hashes), len(common) - 1)
        weight = np.where(common[at] == hashes, counts[at], 0)
    return hashes[np.argsort(weight, kind="stable")[:size]]


def signatures(texts: DataFrame, shingle: int, similarity: float) -> DataFrame:
    """(doc_id, set_id, fp, n, keys, sketch) of every row of (doc_id, text)."""
    common, counts = repeated(texts, shingle)

    def run(batches):
        for b in batches:
            rows, keys, sketches = [], [], []
            for text in binary_list(b.column(1)):
                hashes = shingle_set(text, shingle)
                rows.append([set_id(hashes), fingerprint(hashes), len(hashes)])
                keys.append(prefix(hashes, common, counts, similarity).view(np.int64))
                sketches.append(sketch(hashes))
            cells = np.array(rows, np.int64).reshape(-1, 3)
            yield pa.RecordBatch.from_arrays([b.column(0), *map(pa.array, cells.T.copy()), pa.array(keys, pa.list_(pa.int64())), pa.array(sketches, pa.binary())], ["doc_id", "set_id", "fp", "n", "keys", "sketch"])

    return texts.mapInArrow(thrifty(run), "doc_id long, set_id long, fp long, n long, keys array<long>, sketch binary")


def spanning(ids: np.ndarray, fps: np.ndarray, reach: int):
    """Edges of the minimum spanning forest of one file under the complete distance, cut at reach."""
    near, link = np.bitwise_count(fps ^ fps[0]).astype(np.int16), np.zeros(len(fps), np.int64)
    near[0] = 999  # taken
    for _ in range(len(fps) - 1):
        at = int(near.argmin())
        if near[at] <= reach:
            yield ids[link[at]], ids[at]
        far = np.bitwise_count(fps ^ fps[at]).astype(np.int16)
        closer = (far < near) & (near < 999)
        near[closer], link[closer] = far[closer], at
        near[at] = 999


def alike(n: np.ndarray, m, similarity: float) -> np.ndarray:
    """Whether sets of these sizes can reach the similarity."""
    return np.minimum(n, m) >= similarity * np.maximum(n, m) - 1e-6


def file_edges(keys: np.ndarray, ids: np.ndarray, fps: np.ndarray, ns: np.ndarray, reach: int, similarity: float, small: int = 8) -> np.ndarray:
    """Candidate edges (rows of two ids) within runs of equal keys."""
    edge = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
    sizes = np.diff(np.append(edge, len(keys)))
    few = np.repeat(sizes <= small, sizes)
    k, i, n = keys[few], ids[few], ns[few]
    out = [np.empty((0, 2), np.int64)]
    for step in range(1, min(small, len(k))):
        fit = (k[:-step] == k[step:]) & alike(n[:-step], n[step:], similarity)
        out.append(np.stack([i[:-step][fit], i[step:][fit]], axis=1))
    for at, size in zip(edge[sizes > small], sizes[sizes > small]):
        out.append(np.array(list(spanning(ids[at : at + size], fps[at : at + size], reach)), np.int64).reshape(-1, 2))
    return np.unique(np.sort(np.concatenate(out), axis=1), axis=0)


def blocked(rows: DataFrame, block: int) -> DataFrame:
    """Files of more than `block` rows cut into blocks of about that size, every two blocks of a file making one new file; other files as they are."""
    sizes = materialize(rows.groupBy("key").count().where(F.col("count") > block).select("key", F.ceil(F.col("count") / block).cast("int").alias("blocks")), "files")
    if sizes.isEmpty():
        return rows
    own = rows.join(sizes, "key").withColumn("own", F.pmod(F.xxhash64("set_id"), "blocks").cast("int"))
    met = own.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).where("own <> other or blocks = 1")
    cut = met.select(F.xxhash64("key", F.least("own", "other"), F.greatest("own", "other")).alias("key"), *rows.columns[1:])
    return rows.join(sizes, "key", "left_anti").unionByName(cut)


def by_file(rows: DataFrame, work, schema: str) -> DataFrame:
    """work(keys, ...) over whole files, given the columns of rows as arrays."""

    def run(batches):
        held = None
        for b in simhash._closed(batches):
            if b is not None:
                held = pa.concat_tables([*([] if held is None else [held]), pa.Table.from_batches([b])])
                if held.num_rows < 50_000 and held.nbytes < HELD_BYTES:
                    continue
            if held is None or not held.num_rows:
                continue
            keys = held.column(0).to_numpy()
            cut = int(np.searchsorted(keys, keys[-1])) if b is not None else len(keys)  # the last run may go on
            ready, held = held.slice(0, cut), held.slice(cut)
            if cut:
                yield from work(*[c.to_numpy() for c in ready.combine_chunks().columns])

    return rows.repartition("key").sortWithinPartitions("key").mapInArrow(thrifty(run), schema)


def first_edges(files: DataFrame, reach: int, similarity: float, small: int = 8) -> DataFrame:
    """Candidate edges (null, a, b), and the rows (key, set_id, n) of files that yielded only a forest."""

    def work(keys, ids, fps, ns):
        pairs = file_edges(keys, ids, fps.view(np.uint64), ns, reach, similarity, small)
        edge = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
        sizes = np.diff(np.append(edge, len(keys)))
        many = np.repeat(sizes > small, sizes)
        yield pa.RecordBatch.from_arrays([pa.nulls(len(pairs), pa.int64()), pa.array(pairs[:, 0].copy()), pa.array(pairs[:, 1].copy())], ["key", "a", "b"])
        yield pa.RecordBatch.from_arrays([pa.array(keys[many]), pa.array(ids[many]), pa.array(ns[many])], ["key", "a", "b"])

    return by_file(files, work, "key long, a long, b long")


def apart(ids: np.ndarray, ns: np.ndarray, roots: np.ndarray, sketches: list[bytes], similarity: float):
    """All pairs of one file whose components differ and whose sizes and sketches allow the similarity, in pieces."""
    words = [np.frombuffer(x, np.uint64) for x in sketches]
    size = np.fromiter(map(len, words), np.int64, len(words))
    members = {w: np.flatnonzero(size == w) for w in np.unique(size).tolist()}
    stacked = {w: np.stack([words[i] for i in at]) for w, at in members.items()}
    _, which, many = np.unique(roots, return_inverse=True, return_counts=True)
    for x in np.flatnonzero(which != many.argmax()):  # every such pair has an end outside the largest component
        for w, at in members.items():
            fit = np.flatnonzero((which[at] != which[x]) & alike(ns[at], ns[x], similarity))
            if len(fit):
                near = possible(ns[at[fit]], ns[x], differing(words[x], stacked[w][fit]), similarity)
                other = ids[at[fit[near]]]
                if len(other):
                    yield np.stack([np.minimum(other, ids[x]), np.maximum(other, ids[x])], axis=1)


def unlike_removed(met: DataFrame, nodes: DataFrame, similarity: float) -> DataFrame:
    """The pairs (a, b) whose sketches allow the similarity."""
    n = met.count()
    side = lambda c: nodes.select(F.col("set_id").alias(c), F.col("n").alias(f"n{c}"), F.col("sketch").alias(f"s{c}"))
    both = salted_join(salted_join(met, side("a"), "a", "b", n), side("b"), "b", "a", n).select("a", "b", "na", "nb", "sa", "sb")

    def run(batches):
        for b in batches:
            na, nb = b.column(2).to_numpy(), b.column(3).to_numpy()
            bits = np.array([differing(np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)[None, :])[0] for x, y in zip(b.column(4).to_pylist(), b.column(5).to_pylist())], np.int64)
            yield pa.RecordBatch.from_arrays(b.columns[:2], ["a", "b"]).filter(pa.array(possible(na, nb, bits, similarity)))

    return both.mapInArrow(thrifty(run), "a long, b long")


def joining(ids: np.ndarray, ns: np.ndarray, roots: np.ndarray, sketches: list[bytes], sets: list[np.ndarray], similarity: float) -> list[tuple[int, int]]:
    """Verified edges that join the components of one file as far as its pairs do: at most one less than its components."""
    at = {x: i for i, x in enumerate(ids.tolist())}
    sizes = np.fromiter(map(len, sets), np.int64, len(sets))
    _, codes = np.unique(np.concatenate(sets), return_inverse=True)
    first = np.concatenate([[0], np.cumsum(sizes)])
    which = np.unique(roots, return_inverse=True)[1]
    seen = np.zeros(int(codes.max(initial=0)) + 1, bool)
    out = []
    for pairs in apart(ids, ns, roots, sketches, similarity):
        ends = np.array([[at[x] for x in pair] for pair in pairs.tolist()], np.int64)
        same, counts = np.unique(ends, return_counts=True)
        x = int(same[counts.argmax()])  # the text that all these pairs share
        own = codes[first[x] : first[x + 1]]
        seen[own] = True
        for y in (ends.sum(axis=1) - x).tolist():
            if which[x] != which[y]:
                both = int(seen[codes[first[y] : first[y + 1]]].sum())
                if both / (sizes[x] + sizes[y] - both) >= similarity:
                    out.append((ids[x], ids[y]) if ids[x] < ids[y] else (ids[y], ids[x]))
                    which[which == which[y]] = which[x]
        seen[own] = False
    return out


def still_apart(members: DataFrame, roots: DataFrame, nodes: DataFrame, similarity: float) -> DataFrame:
    """Rows (key, set_id, n, root, sketch) of files with pairs in different components whose sketches allow the similarity: those of such pairs."""
    labels = nodes.select("set_id").join(roots.withColumnRenamed("node", "set_id"), "set_id", "left").select("set_id", F.coalesce("root", "set_id").alias("root"))
    named = members.join(labels, "set_id").select("key", "set_id", "n", "root")
    mixed = named.groupBy("key").agg(F.min("root").alias("low"), F.max("root").alias("high")).where("low <> high").select("key")

    def work(keys, ids, ns, roots, sketches):
        for at, to in runs(keys):
            found = [np.empty(0, np.int64)]
            for pairs in apart(ids[at:to], ns[at:to], roots[at:to], sketches[at:to].tolist(), similarity):
                found.append(pairs.ravel())
                if len(found) > 256:
                    found = [np.unique(np.concatenate(found))]
            meant = at + np.flatnonzero(np.isin(ids[at:to], np.concatenate(found)))
            if len(meant):
                yield pa.RecordBatch.from_arrays([pa.array(keys[meant]), pa.array(ids[meant]), pa.array(ns[meant]), pa.array(roots[meant]), pa.array(sketches[meant].tolist(), pa.binary())], ["key", "set_id", "n", "root", "sketch"])

    rows = named.join(mixed, "key", "left_semi").join(nodes.select("set_id", "sketch"), "set_id")
    return by_file(rows.select("key", "set_id", "n", "root", "sketch"), work, "key long, set_id long, n long, root long, sketch binary")


def runs(keys: np.ndarray) -> list[tuple[int, int]]:
    """(first, end) of each run of equal keys."""
    edge = np.append(np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])), len(keys)).tolist()
    return list(zip(edge[:-1], edge[1:]))


def joined(rows: DataFrame, held: DataFrame, similarity: float) -> DataFrame:
    """Edges (a, b) of near-copies that join different components of a file. held: (set_id, hashes)."""

    def work(keys, ids, ns, roots, sketches, sets):
        found = [e for at, to in runs(keys) for e in joining(ids[at:to], ns[at:to], roots[at:to], sketches[at:to].tolist(), list(sets[at:to]), similarity)]
        edges = np.array(found, np.int64).reshape(-1, 2)
        yield pa.RecordBatch.from_arrays([pa.array(edges[:, 0].copy()), pa.array(edges[:, 1].copy())], ["a", "b"])

    whole = salted_join(rows, held, "set_id", "key", rows.count()).select("key", "set_id", "n", "root", "sketch", "hashes")
    return by_file(whole, work, "a long, b long").distinct()


def simhash_links(nodes: DataFrame) -> DataFrame:
    """Pairs (a, b) of sets that multi-index hashing of their fingerprints links: those of one fingerprint by its smallest set, near fingerprints by theirs."""
    owners = materialize(nodes.groupBy("fp").agg(F.min("set_id").alias("own")), "fingerprints")
    side = lambda c: owners.select(F.col("fp").alias(c), F.col("own").alias(f"own{c}"))
    near = simhash.links(owners.select("fp")).join(side("a"), "a").join(side("b"), "b").select("owna", "ownb")
    same = nodes.join(owners, "fp").where("set_id <> own").select("set_id", "own")
    return near.union(same).toDF("x", "y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))


def near_copies(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 5, similarity: float = 0.8, reach: int = 18, split_at: int = 4_000) -> DataFrame:
    """(doc_id, component_id) of every row with an id; component_id is the smallest doc_id reachable over near-copies."""
    df = df.where(F.col(id_col).isNotNull())
    texts = df.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    signed, signed_path = stored(signatures(texts, shingle, similarity), "signatures")
    own = materialize(signed.select("doc_id", "set_id"), "classes")
    rows = own.count()
    nodes = materialize(signed.groupBy("set_id").agg(F.min("doc_id").alias("low"), F.min("fp").alias("fp"), F.min("n").alias("n"), F.min("keys").alias("keys"), F.min("sketch").alias("sketch")), "sets")  # a text each, however many copies it has
    drop_path(df.sparkSession, signed_path)
    files = nodes.select(F.explode("keys").alias("key"), "set_id", "fp", "n")
    first = materialize(first_edges(blocked(files, split_at), reach, similarity), "candidates")
    met = materialize(simhash_links(nodes).unionByName(first.where("key is null").select("a", "b")).distinct(), "met")

    def shingles(ends: DataFrame) -> DataFrame:
        """(set_id, hashes) of these sets."""
        wanted = nodes.join(ends, "set_id").select(F.col("low").alias("doc_id")).distinct()
        return materialize(texts.join(wanted, "doc_id").select("text").mapInArrow(thrifty(sets), "set_id long, hashes array<long>"), "shingles").dropDuplicates(["set_id"])

    def verified(met: DataFrame) -> DataFrame:
        """The pairs that reach the similarity. A text with many pairs is sent to several tasks, so none gets all of them."""
        n = met.count()
        held = shingles(met.select(F.col("a").alias("set_id")).union(met.select("b")).distinct())
        side = lambda c: held.select(F.col("set_id").alias(c), F.col("hashes").alias(f"h{c}"))
        both = F.size(F.array_intersect("ha", "hb"))
        share = both / (F.size("ha") + F.size("hb") - both)
        return salted_join(salted_join(met, side("a"), "a", "b", n), side("b"), "b", "a", n).where(share >= similarity).select("a", "b")

    def sets(batches):
        for b in batches:
            found = [shingle_set(t, shingle) for t in binary_list(b.column(0))]
            yield pa.RecordBatch.from_arrays([pa.array(list(map(set_id, found)), pa.int64()), pa.array([x.view(np.int64) for x in found], pa.list_(pa.int64()))], ["set_id", "hashes"])

    roots = connected_components(verified(materialize(unlike_removed(met, nodes, similarity), "alike")))
    members = first.where("key is not null").select("key", F.col("a").alias("set_id"), F.col("b").alias("n"))
    left = materialize(still_apart(members, roots, nodes, similarity), "apart")
    if not left.isEmpty():
        found = joined(left, shingles(left.select("set_id").distinct()), similarity)
        roots = connected_components(roots.select(F.col("node").alias("a"), F.col("root").alias("b")).unionByName(found))
    named = nodes.select("set_id", "low").join(roots.withColumnRenamed("node", "set_id"), "set_id", "left").withColumn("root", F.coalesce("root", "set_id"))
    lowest = named.groupBy("root").agg(F.min("low").alias("component_id"))
    classes = salted_join(named, lowest, "root", "set_id", rows).select("set_id", "component_id")
    return salted_join(own.select("doc_id", "set_id"), classes, "set_id", "doc_id", rows).select("doc_id", "component_id")


def keep_one(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows of df that stay: of each group of near-copies the one with the smallest id; rows without id stay."""
    return simhash.keep_lowest(df, near_copies(df, id_col, text_col, **options), id_col)
