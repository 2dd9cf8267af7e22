"""Language identification by a bidirectional gated recurrent network over bytes.

The network labels every byte of a text; the text's probabilities are the mean
over its bytes. A text is read whole, in stretches of at most `STRETCH` bytes;
a state enters a stretch after `LEAD` bytes of what stands before it (behind
it, for the backward direction), which only warm it up. Stretches of like
length advance together. Training is plain numpy: backpropagation through time
over windows of `WINDOW` bytes, Adam updates, on a bounded sample of labelled rows
(`sample_docs` texts, as many of each language, of each one piece of `piece_chars` characters).

Defined results: a null text or one without a letter is `und` with score 0; so
is every text if there was nothing to learn from; rows without language are not
learned from; null ids fall in the fold of the empty text; repeated rows are
each predicted; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import binary_list, fold, thrifty

WINDOW, STRETCH, LEAD = 64, 960, 32
BLOCK = 1024
#: Rows of a batch that are held as bytes at once.
ROWS = 2048
LETTER = regex.compile(r"\p{L}")
UND = "und"


def _gates(x: np.ndarray) -> np.ndarray:
    """Logistic function, in place."""
    x *= np.float32(0.5)
    np.tanh(x, out=x)
    x += np.float32(1)
    x *= np.float32(0.5)
    return x


class Direction:
    """One direction of the network. table: what each byte adds to the gates; recur: what the state adds."""

    def __init__(self, table: np.ndarray, recur: np.ndarray):
        self.table, self.recur = table, recur

    def states(self, text: np.ndarray, mask: np.ndarray | None, keep: list | None = None) -> np.ndarray:
        """States after each step of text (steps, windows); a masked step leaves the state at zero."""
        steps, n = text.shape
        size = len(self.recur)
        out = np.empty((steps, n, size), np.float32)
        h = np.zeros((n, size), np.float32)
        for t in range(steps):
            x, g = self.table[text[t]], h @ self.recur
            x[:, : 2 * size] += g[:, : 2 * size]
            gates = _gates(x[:, : 2 * size])
            update, reset = gates[:, :size], gates[:, size:]
            fresh = np.tanh(x[:, 2 * size :] + reset * g[:, 2 * size :])
            if keep is not None:
                keep.append((h, update, reset, fresh, g[:, 2 * size :]))
            h = fresh + update * (h - fresh)
            if mask is not None:
                h *= mask[t][:, None]
            out[t] = h
        return out

    def outputs(self, text: np.ndarray, mask: np.ndarray | None, weights: np.ndarray) -> np.ndarray:
        """states() @ weights, without the states: gates apart from each other, so that every operation runs over whole buffers in place."""
        steps, n = text.shape
        size = len(self.recur)
        half = np.array([0.5, 0.5, 1], np.float32)[:, None, None]  # of the two logistic gates, as half a hyperbolic tangent
        table = self.table.reshape(-1, 3, size).transpose(1, 0, 2) * half
        recur = self.recur.reshape(size, 3, size).transpose(1, 0, 2) * half
        out, h = np.empty((steps, n, weights.shape[1]), np.float32), np.zeros((n, size), np.float32)
        x, g = np.empty((3, n, size), np.float32), np.empty((3, n, size), np.float32)
        gates, (update, reset, fresh) = x[:2], x
        for t in range(steps):
            for i in range(3):
                np.take(table[i], text[t], axis=0, out=x[i], mode="clip")
            np.matmul(h, recur, out=g)
            gates += g[:2]
            np.tanh(gates, out=gates)
            gates *= np.float32(0.5)
            gates += np.float32(0.5)
            reset *= g[2]
            fresh += reset
            np.tanh(fresh, out=fresh)
            h -= fresh
            h *= update
            h += fresh
            if mask is not None:
                h *= mask[t][:, None]
            np.matmul(h, weights, out=out[t])
        return out

    def gradients(self, text: np.ndarray, kept: list, d_states: np.ndarray) -> list[np.ndarray]:
        """Backpropagation through time: gradients of table and recur."""
        size = len(self.recur)
        d_table, d_recur = np.zeros_like(self.table), np.zeros_like(self.recur)
        d_h = np.zeros_like(d_states[0])
        for t in range(len(kept) - 1, -1, -1):
            h, update, reset, fresh, g = kept[t]
            d_h = d_h + d_states[t]
            d_fresh = d_h * (1 - update) * (1 - fresh * fresh)
            d_update = d_h * (h - fresh) * update * (1 - update)
            d_reset = d_fresh * g * reset * (1 - reset)
            d_g = np.concatenate([d_update, d_reset, d_fresh * reset], axis=1)
            np.add.at(d_table, text[t], np.concatenate([d_update, d_reset, d_fresh], axis=1))
            d_recur += h.T @ d_g
            d_h = d_h * update + d_g @ self.recur.T
        return [d_table, d_recur]


class Network:
    def __init__(self, labels: list[str], size: int = 8, seed: int = 42):
        rng = np.random.default_rng(seed)
        draw = lambda *shape: (rng.standard_normal(shape) * 0.3).astype(np.float32)
        self.labels = labels
        self.weights = [draw(256, 3 * size), draw(size, 3 * size), draw(256, 3 * size), draw(size, 3 * size), draw(2 * size, len(labels)), np.zeros(len(labels), np.float32)]

    def _pass(self, text: np.ndarray, mask: np.ndarray | None, keep: tuple | None = None):
        w = self.weights
        ahead = Direction(w[0], w[1]).states(text, mask, keep and keep[0])
        back = Direction(w[2], w[3]).states(text[::-1], None if mask is None else mask[::-1], keep and keep[1])[::-1]
        size = ahead.shape[2]
        scores = ahead @ w[4][:size] + back @ w[4][size:] + w[5]
        scores -= scores.max(axis=2, keepdims=True)
        np.exp(scores, out=scores)
        scores /= scores.sum(axis=2, keepdims=True)
        return ahead, back, scores

    def position_probabilities(self, text: np.ndarray, mask: np.ndarray | None = None) -> np.ndarray:
        """(steps, windows, labels) for bytes laid out as (steps, windows)."""
        w, size = self.weights, len(self.weights[1])
        scores = Direction(w[0], w[1]).outputs(text, mask, w[4][:size])
        scores += Direction(w[2], w[3]).outputs(text[::-1], None if mask is None else mask[::-1], w[4][size:])[::-1]
        scores += w[5]
        scores -= scores.max(axis=2, keepdims=True)
        np.exp(scores, out=scores)
        scores /= scores.sum(axis=2, keepdims=True)
        return scores

    def step(self, text: np.ndarray, labels: np.ndarray) -> tuple[float, list[np.ndarray]]:
        """Mean loss over all positions, and the gradients."""
        kept: tuple[list, list] = ([], [])
        ahead, back, p = self._pass(text, None, kept)
        steps, n, _ = p.shape
        loss = -np.log(np.maximum(p[:, np.arange(n), labels], 1e-9)).mean()
        d = p.copy()
        d[:, np.arange(n), labels] -= 1
        d /= np.float32(steps * n)
        w, size = self.weights, ahead.shape[2]
        flat = d.reshape(-1, d.shape[2])
        d_out = np.concatenate([ahead.reshape(-1, size).T @ flat, back.reshape(-1, size).T @ flat])
        first = Direction(w[0], w[1]).gradients(text, kept[0], d @ w[4][:size].T)
        second = Direction(w[2], w[3]).gradients(text[::-1], kept[1], (d @ w[4][size:].T)[::-1])
        return float(loss), [*first, *second, d_out, flat.sum(axis=0)]

    def fit(self, windows: np.ndarray, labels: np.ndarray, epochs: int = 6, batch: int = 256, rate: float = 0.02, seed: int = 42) -> float:
        rng = np.random.default_rng(seed)
        mean, var = ([np.zeros_like(w) for w in self.weights] for _ in range(2))
        done, loss = 0, 0.0
        for _ in range(epochs):
            order = rng.permutation(len(windows))
            for at in range(0, len(order), batch):
                own = order[at : at + batch]
                loss, grads = self.step(np.ascontiguousarray(windows[own].T), labels[own])
                done += 1
                for w, g, m, v in zip(self.weights, grads, mean, var):
                    m += 0.1 * (g - m)
                    v += 0.01 * (g * g - v)
                    w -= (rate * (m / (1 - 0.9**done)) / (np.sqrt(v / (1 - 0.99**done)) + 1e-7)).astype(np.float32)
        return loss

    def predict(self, texts: list[bytes | None]) -> tuple[list[str], list[float]]:
        """The label of each whole text and its pooled probability."""
        names, scores = [UND] * len(texts), [0.0] * len(texts)
        live = [i for i, t in enumerate(texts) if t and LETTER.search(t.decode("utf-8", "replace"))] if self.labels else []
        for at in _groups([len(texts[i]) for i in live], 1 << 22):
            own = live[at]
            pooled = self._pooled([texts[i] for i in own])
            for i, p in zip(own, pooled):
                best = int(p.argmax())
                names[i], scores[i] = self.labels[best], min(1.0, float(p[best]))
        return names, scores

    def _pooled(self, texts: list[bytes]) -> np.ndarray:
        stretches = []  # (bytes read, text, first counted byte, counted bytes)
        for n, t in enumerate(texts):
            for at in range(0, len(t), STRETCH):
                begin, end = max(0, at - LEAD), min(len(t), at + STRETCH)
                stretches.append((t[begin : end + LEAD], n, at - begin, end - at))
        stretches.sort(key=lambda s: len(s[0]))
        sums = np.zeros((len(texts), len(self.labels)))
        for at in range(0, len(stretches), BLOCK):
            own = stretches[at : at + BLOCK]
            steps = len(own[-1][0])
            laid = np.frombuffer(b"".join(s[0].ljust(steps, b"\0") for s in own), np.uint8).reshape(len(own), steps)
            place = np.arange(steps)[:, None]
            filled, lead, counted = (np.array(x) for x in zip(*((len(s[0]), s[2], s[3]) for s in own)))
            p = self.position_probabilities(np.ascontiguousarray(laid.T), (place < filled).astype(np.float32) if (filled < steps).any() else None)
            weight = ((place >= lead) & (place < lead + counted)).astype(np.float32)
            np.add.at(sums, [s[1] for s in own], np.einsum("tnl,tn->nl", p, weight))
        return sums / np.array([len(t) for t in texts])[:, None]


def _groups(sizes: list[int], most: int):
    """Slices of about `most` bytes."""
    start, held = 0, 0
    for i, n in enumerate(sizes):
        held += n
        if held >= most:
            yield slice(start, i + 1)
            start, held = i + 1, 0
    if start < len(sizes):
        yield slice(start, len(sizes))


def train(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "lang", folds: int = 5, sample_docs: int = 3_000, piece_chars: int = 600, size: int = 8, seed: int = 42) -> Network:
    """A network learned from rows outside fold 0: about sample_docs of them, shared evenly by the languages, of each at most piece_chars characters at a hashed place."""
    rows = df.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), F.col(label_col).cast("string").alias("label"))
    rows = rows.where((fold(F.col("id"), folds) != 0) & F.col("label").isNotNull() & F.col("text").isNotNull())
    sizes = rows.groupBy("label").agg(F.count("*").alias("n"))  # a row for each language
    each = max(1, sample_docs // max(1, sizes.count()))
    place = F.pmod(F.xxhash64("id", F.lit(1)), F.greatest(F.lit(1), F.length("text") - piece_chars)) + 1
    share = F.pmod(F.xxhash64("id", "text"), F.col("n")) < each
    found = rows.join(F.broadcast(sizes), "label").where(share).select("label", F.substring("text", place.cast("int"), F.lit(piece_chars)).alias("piece")).limit(2 * sample_docs).toArrow().to_pydict()
    pairs = sorted(zip(found["label"], found["piece"]))
    labels = sorted({lab for lab, _ in pairs})
    windows, own = [], []
    for label, piece in pairs:
        raw = piece.encode()
        raw = raw * (WINDOW // max(1, len(raw)) + 1) if 0 < len(raw) < WINDOW else raw
        for at in range(0, len(raw), WINDOW):
            at = min(at, len(raw) - WINDOW)  # the last window ends with the piece
            windows.append(raw[at : at + WINDOW])
            own.append(labels.index(label))
    net = Network(labels, size, seed)
    if windows:
        net.fit(np.frombuffer(b"".join(windows), np.uint8).reshape(-1, WINDOW), np.array(own))
    return net


def identify(df: DataFrame, net: Network, id_col: str = "doc_id", text_col: str = "text", folds: int = 5, keep: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, held_out, lang_pred, score of every row, and the columns named in keep unchanged."""
    held = df.sparkSession.sparkContext.broadcast(net)

    def run(batches):
        for whole in batches:
            for at in range(0, whole.num_rows, ROWS):
                b = whole.slice(at, ROWS)
                names, scores = held.value.predict(binary_list(b.column(place)))
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(names), pa.array(scores, pa.float64()), *b.columns[first:]], ["doc_id", "held_out", "lang_pred", "score", *keep])

    kept = text_col in keep  # then the text moves once
    place, first = (2 + keep.index(text_col), 2) if kept else (2, 3)
    rows = df.select(F.col(id_col).cast("long").alias("doc_id"), (fold(F.col(id_col), folds) == 0).alias("held_out"), *([] if kept else [F.col(text_col).alias("__text")]), *[F.col(c) for c in keep])
    types = dict(df.dtypes)
    return rows.mapInArrow(thrifty(run), ", ".join(["doc_id long, held_out boolean, lang_pred string, score double", *[f"`{c}` {types[c]}" for c in keep]]))
