"""Byte-level BPE by dynamic programming over prefixes.

In a valid encoding every two neighbouring tokens would also be left apart if
their bytes were encoded alone, and an encoding in which all neighbours are so
is the only one. Each prefix of a piece therefore has one last token, and it
can be found from the last tokens of shorter prefixes alone. Keeping the last
tokens makes an append exact without looking back, and an edit costs only
what lies behind it until the last tokens agree again.

Defined results: a null text counts as empty; an empty text has no tokens;
repeated rows are each encoded; no text holds special tokens; an empty table
gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import thrifty


def read_ranks(path: str) -> dict[bytes, int]:
    """A public rank file: base64 bytes and rank on each line. It is read on the driver, from its place in the installation."""
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


class Vocabulary:
    """Ranks with the tables that the search needs."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks, self.pattern = ranks, pattern
        self.bytes_of = {i: b for b, i in ranks.items()}
        #: What token, if any, each beginning of a token is; a missing key ends a search for longer ones.
        self.starts: dict[bytes, int] = {}
        for token in ranks:
            for n in range(1, len(token) + 1):
                self.starts.setdefault(token[:n], ranks.get(token[:n], -1))
        self.longest = max(map(len, ranks), default=0)
        self._apart: dict[int, bool] = {}

    def merged(self, piece: bytes) -> list[int]:
        """The definition: merge the pair of lowest rank, leftmost first, until none is left."""
        parts = [piece[i : i + 1] for i in range(len(piece))]
        while len(parts) > 1:
            best = min(range(len(parts) - 1), key=lambda i: self.ranks.get(parts[i] + parts[i + 1], 1 << 60))
            if parts[best] + parts[best + 1] not in self.ranks:
                break
            parts[best : best + 2] = [parts[best] + parts[best + 1]]
        return [self.ranks[p] for p in parts]

    def apart(self, left: int, right: int) -> bool:
        """Whether two neighbouring tokens stay as they are."""
        key = left << 32 | right
        known = self._apart.get(key)
        if known is None:
            if len(self._apart) > 1_000_000:
                self._apart.clear()
            known = self._apart[key] = self.merged(self.bytes_of[left] + self.bytes_of[right]) == [left, right]
        return known


def fill(v: Vocabulary, piece: bytes, last: list[int], begin: int = 0, known: int = 0) -> list[int]:
    """Set the last token of every prefix longer than known; tokens that begin before `begin` are too short to matter."""
    starts, apart, n = v.starts.get, v._apart.get, len(piece)
    for begin in range(begin, n):
        before = last[begin]
        if begin and before < 0:
            continue
        for end in range(begin + 1, n + 1):
            token = starts(piece[begin:end])
            if token is None:
                break
            if token >= 0 and end > known and last[end] < 0:
                if begin:
                    fits = apart(before << 32 | token)
                    if not (v.apart(before, token) if fits is None else fits):
                        continue
                last[end] = token
    return last


def trace(v: Vocabulary, piece: bytes, last: list[int]) -> list[int]:
    """The tokens of the whole piece, from its last tokens backwards."""
    out, end = [], len(piece)
    while end:
        out.append(last[end])
        end -= len(v.bytes_of[out[-1]])
    return out[::-1]


class PrefixEncoder:
    """The last token of every prefix of a growing piece."""

    def __init__(self, vocabulary: Vocabulary, piece: bytes = b""):
        self.v, self.piece, self.last = vocabulary, b"", [-1]
        self.append(piece)

    def append(self, more: bytes) -> None:
        """Add bytes at the end; the prefixes known so far keep their tokens."""
        known = len(self.piece)
        self.piece += more
        self.last += [-1] * len(more)
        fill(self.v, self.piece, self.last, max(0, known - self.v.longest), known)

    def edit(self, start: int, stop: int, new: bytes) -> None:
        """Replace piece[start:stop]. Prefixes up to start stay; behind the edit, work ends once the last tokens agree with the old ones."""
        old_piece, old_last, tail = self.piece, self.last, self.piece[stop:]
        self.piece, self.last = old_piece[:start], old_last[: start + 1]
        self.append(new)
        shift, same = start + len(new) - stop, 0
        for at in range(0, len(tail), 64):
            self.append(tail[at : at + 64])
            for end in range(stop + at + 1, min(stop + at + 64, len(old_piece)) + 1):
                same = same + 1 if self.last[end + shift] == old_last[end] else 0
            if same >= 2 * self.v.longest:  # every later token begins where both agree
                rest = stop + at + 64
                if rest < len(old_piece):
                    self.piece += old_piece[rest:]
                    self.last += old_last[rest + 1 :]
                return

    def tokens(self) -> list[int]:
        return trace(self.v, self.piece, self.last)


class _Packed(dict):
    """Little-endian ids of each piece; forgets all beyond `most`, so it stays bounded."""

    def __init__(self, vocabulary: Vocabulary, most: int = 400_000):
        super().__init__()
        self.v, self.most = vocabulary, most

    def __missing__(self, piece: str) -> bytes:
        raw = piece.encode()
        own = self.v.ranks.get(raw)
        ids = [own] if own is not None else trace(self.v, raw, fill(self.v, raw, [-1] * (len(raw) + 1)))
        packed = np.array(ids, "<u4").tobytes()
        if len(raw) <= 64:
            if len(self) >= self.most:
                self.clear()
            self[piece] = packed
        return packed


class Codec:
    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks, self.pattern = ranks, pattern
        self._ready = False

    def __getstate__(self):
        return {"ranks": self.ranks, "pattern": self.pattern, "_ready": False}

    def _prepare(self):
        if not self._ready:
            self.v = Vocabulary(self.ranks, self.pattern)
            self.find = regex.compile(self.pattern).findall
            self.packed = _Packed(self.v)
            self._ready = True

    def encode(self, text: str) -> bytes:
        """Ids of the text as little-endian unsigned 32-bit integers."""
        self._prepare()
        return b"".join(map(self.packed.__getitem__, self.find(text)))

    def decode(self, ids: bytes) -> bytes:
        self._prepare()
        return b"".join(map(self.v.bytes_of.__getitem__, np.frombuffer(ids, "<u4").tolist()))


def encode_documents(df: DataFrame, ranks: dict[bytes, int], pattern: str, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False, keep: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 (with_ids: and ids array<int>) of every row, and the columns named in keep."""
    held = df.sparkSession.sparkContext.broadcast(Codec(ranks, pattern))  # the size of the vocabulary

    def run(batches):
        codec = held.value
        names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", *["ids"] * with_ids, *keep]
        for whole in batches:
            for at in range(0, whole.num_rows, 1_000):
                b = whole.slice(at, 1_000)
                packed = [codec.encode(t or "") for t in b.column(1).to_pylist()]
                sha = lambda x: hashlib.sha256(x).hexdigest()
                out = [b.column(0), pa.array([len(p) // 4 for p in packed], pa.int64()), pa.array([sha(p) for p in packed]), pa.array([sha(codec.decode(p)) for p in packed])]
                if with_ids:
                    ends = np.cumsum([0, *(len(p) // 4 for p in packed)]).astype(np.int32)
                    out.append(pa.ListArray.from_arrays(pa.array(ends), pa.array(np.frombuffer(b"".join(packed), "<u4").astype(np.int32))))
                yield pa.RecordBatch.from_arrays([*out, *b.columns[2:]], names)

    types = dict(df.dtypes)
    schema = ["doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string", *["ids array<int>"] * with_ids, *[f"`{c}` {types[c]}" for c in keep]]
    return df.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("__text"), *[F.col(c) for c in keep]).mapInArrow(thrifty(run), ", ".join(schema))
