"""Document quality by attention over passages.

A document is a bag of passages of ``PASSAGE`` words. Each passage is encoded from
its bytes: shares of byte values in 64 classes, hashed byte trigrams, hashed words,
mean word length and how much of it repeats words met before in the document. A
dense layer gives the passage representation h; gated attention
softmax(w . (tanh(V h) * sigmoid(U h))) weighs the passages, and a logistic unit
scores the weighted sum. Only document labels are needed: the attention learns
which passages speak for them.

The model is fitted on the driver over at most ``max_train`` labelled documents,
the first in the order of a hash of their id (a documented bound). Features, not
texts, come to the driver, of every passage of those documents, in half precision;
they are widened a batch at a time. Scoring reads every passage of every document.

Defined results: null or empty text is one empty passage; rows with a null id are
scored, not learned from, and not held out; with no usable label every score is 0.5.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from grove.llm import text_arrays as ta

PASSAGE = 128
_TRI, _WORD = 192, 128
_CLASS = np.zeros(256, np.int64)
_CLASS[:] = 63
_CLASS[97:123], _CLASS[65:91], _CLASS[48:58] = 0, 1, 2
for _n, _c in enumerate([32, *range(9, 14), *range(33, 48), *range(58, 65), *range(91, 97), *range(123, 127)]):
    _CLASS[_c] = 3 + _n
WIDTH = 64 + _TRI + _WORD + 4


def encode(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(passages, WIDTH) float32 features, and per row + 1 the index of its first passage."""
    raw, offs = ta.text_bytes(column)
    start, end, first = ta.words(raw, offs)
    rows = len(offs) - 1
    n_words = np.diff(first)
    count = np.maximum(1, -(-n_words // PASSAGE))
    begin = np.concatenate([[0], np.cumsum(count)])
    total = int(begin[-1])
    out = np.zeros((total, WIDTH), np.float32)
    if len(raw) == 0:
        return out, begin
    owner = np.repeat(np.arange(rows), n_words)
    of_word = begin[owner] + (np.arange(len(start)) - first[owner]) // PASSAGE
    # a byte belongs to the passage of the word that begins last before it
    step = np.flatnonzero((np.arange(len(start)) - first[owner]) % PASSAGE == 0)
    step = step[step != first[owner[step]]]
    jump = np.zeros(len(raw) + 1, np.int64)
    jump[start[step]] = 1
    within = np.cumsum(jump[:-1])
    row_of = np.repeat(np.arange(rows), np.diff(offs))
    base = np.zeros(rows, np.int64)
    full = np.diff(offs) > 0
    base[full] = within[offs[:-1][full]]
    passage = begin[row_of] + within - base[row_of]
    size = np.bincount(passage, minlength=total).astype(np.float32)
    out[:, :64] = np.bincount(passage * 64 + _CLASS[raw], minlength=total * 64).reshape(total, 64)
    low = ta._BYTE[raw] >> np.uint64(33)
    if len(raw) > 2:
        tri = (low[:-2] * np.uint64(31) + low[1:-1] * np.uint64(17) + low[2:]) % np.uint64(_TRI)
        own = row_of[:-2] == row_of[2:]
        out[:, 64 : 64 + _TRI] = np.bincount((passage[:-2] * _TRI + tri.astype(np.int64))[own], minlength=total * _TRI).reshape(total, _TRI)
    h = ta.word_hashes(raw, start, end)
    k = 64 + _TRI
    words_in = np.maximum(1, np.bincount(of_word, minlength=total)).astype(np.float32)
    if len(h):
        out[:, k : k + _WORD] = np.bincount(of_word * _WORD + (h % np.uint64(_WORD)).astype(np.int64), minlength=total * _WORD).reshape(total, _WORD)
        key = ta.mix(h + owner.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
        order = np.argsort(key, kind="stable")
        again = np.zeros(len(h), bool)
        again[order[1:]] = key[order[1:]] == key[order[:-1]]
        out[:, -1] = np.bincount(of_word[again], minlength=total) / words_in
        long = (end - start) >= 6
        new = np.bincount(of_word[again & long], minlength=total)
        out[:, -2] = new / np.maximum(1, np.bincount(of_word[long], minlength=total))
        out[:, -3] = np.bincount(of_word, end - start, minlength=total) / words_in / 16
    out[:, : k + _WORD] = np.sqrt(out[:, : k + _WORD] / np.maximum(1, size)[:, None])
    out[:, -4] = np.log1p(size) / 8
    return out, begin


class GatedBags:
    """h = relu(xW + b); a = softmax(w . (tanh(hV) * sigmoid(hU))); p = sigmoid(c . sum(a h) + d)."""

    def __init__(self, hidden: int = 32, gate: int = 16, seed: int = 5):
        rng = np.random.default_rng(seed)
        g = lambda *s: (rng.standard_normal(s) / np.sqrt(s[0])).astype(np.float32)
        self.p = {"W": g(WIDTH, hidden), "b": np.zeros(hidden, np.float32), "V": g(hidden, gate), "U": g(hidden, gate), "w": g(gate), "c": g(hidden), "d": np.zeros(1, np.float32)}
        self.mean, self.scale = np.zeros(WIDTH, np.float32), np.ones(WIDTH, np.float32)
        self.fitted = False

    def forward(self, x: np.ndarray, begin: np.ndarray) -> dict:
        p = self.p
        x = (x - self.mean) / self.scale
        pre = x @ p["W"] + p["b"]
        h = np.maximum(pre, 0)
        t, s = np.tanh(h @ p["V"]), 1 / (1 + np.exp(-(h @ p["U"])))
        e = (t * s) @ p["w"]
        top = np.repeat(np.maximum.reduceat(e, begin[:-1]), np.diff(begin))
        e = np.exp(e - top)
        a = e / np.repeat(np.add.reduceat(e, begin[:-1]), np.diff(begin))
        z = np.add.reduceat(a[:, None] * h, begin[:-1], axis=0)
        y = 1 / (1 + np.exp(-np.clip(z @ p["c"] + p["d"], -30, 30)))
        return {"x": x, "h": h, "t": t, "s": s, "a": a, "z": z, "y": y}

    def score(self, x: np.ndarray, begin: np.ndarray) -> np.ndarray:
        if not self.fitted:
            return np.full(len(begin) - 1, 0.5)
        return self.forward(x, begin)["y"].astype(float)

    def fit(self, x: np.ndarray, begin: np.ndarray, label: np.ndarray, epochs: int = 30, batch: int = 64, rate: float = 3e-3, decay: float = 1e-3, seed: int = 6) -> None:
        total = squares = 0.0
        for at in range(0, len(x), 4096):
            some = x[at : at + 4096].astype(np.float64)
            total, squares = total + some.sum(0), squares + (some * some).sum(0)
        mean = total / len(x)
        self.mean = mean.astype(np.float32)
        self.scale = (np.sqrt(np.maximum(squares / len(x) - mean**2, 0)) + 0.02).astype(np.float32)
        rng = np.random.default_rng(seed)
        m = {k: np.zeros_like(v) for k, v in self.p.items()}
        v = {k: np.zeros_like(q) for k, q in self.p.items()}
        sizes = np.diff(begin)
        step = 0
        for _ in range(epochs):
            order = rng.permutation(len(sizes))
            for k in range(0, len(order), batch):
                bags = order[k : k + batch]
                at = np.concatenate([np.arange(begin[i], begin[i + 1]) for i in bags])
                off = np.concatenate([[0], np.cumsum(sizes[bags])])
                grad = self._gradient(x[at].astype(np.float32), off, label[bags])
                step += 1
                for n, g in grad.items():
                    g = g + (decay * self.p[n] if n in "WVU" else 0)
                    m[n] = 0.9 * m[n] + 0.1 * g
                    v[n] = 0.999 * v[n] + 0.001 * g * g
                    self.p[n] -= (rate * (m[n] / (1 - 0.9**step)) / (np.sqrt(v[n] / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
        self.fitted = True

    def _gradient(self, x: np.ndarray, off: np.ndarray, label: np.ndarray) -> dict:
        p, f = self.p, self.forward(x, off)
        sizes = np.diff(off)
        dy = ((f["y"] - label) / len(label)).astype(np.float32)
        dz = dy[:, None] * p["c"]
        per = np.repeat(dz, sizes, axis=0)
        da = (per * f["h"]).sum(1)
        mean = np.repeat(np.add.reduceat(f["a"] * da, off[:-1]), sizes)
        de = f["a"] * (da - mean)
        gate = de[:, None] * p["w"]
        dt, ds = gate * f["s"] * (1 - f["t"] ** 2), gate * f["t"] * f["s"] * (1 - f["s"])
        dh = f["a"][:, None] * per + dt @ p["V"].T + ds @ p["U"].T
        dh *= f["h"] > 0
        return {"W": f["x"].T @ dh, "b": dh.sum(0), "V": f["h"].T @ dt, "U": f["h"].T @ ds, "w": (f["t"] * f["s"]).T @ de, "c": f["z"].T @ dy, "d": dy.sum(keepdims=True)}


def held_out(column: str = "doc_id"):
    """True where crc32 of the id as text leaves 0 on division by 5; false for a null id."""
    return F.coalesce(F.pmod(F.crc32(F.col(column).cast("string").cast("binary")), F.lit(5)) == 0, F.lit(False))


def _features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for batch in ta.slices(whole, "text"):
            x, begin = encode(batch.column("text"))
            out = [x[a:b].astype(np.float16).tobytes() for a, b in zip(begin[:-1], begin[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column("quality"), pa.array(out, pa.binary())], names=["quality", "x"])


def train(docs: DataFrame, labels: DataFrame, max_train: int = 4000) -> GatedBags:
    """A model from the labelled rows that are not held out."""
    model = GatedBags()
    sample = (
        labels.where("quality is not null and doc_id is not null")
        .where(~held_out())
        .groupBy(F.col("doc_id").cast("long").alias("doc_id"))
        .agg(F.max(F.col("quality").cast("int")).alias("quality"))
        .orderBy(F.xxhash64("doc_id"), "doc_id")
        .limit(max_train)
    )
    rows = ta.whole_texts(docs).select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(sample), "doc_id").select("quality", "text")
    got = rows.mapInArrow(_features, "quality int, x binary").toPandas()
    if got["quality"].nunique() < 2:
        return model
    bags = [np.frombuffer(b, np.float16).reshape(-1, WIDTH) for b in got["x"]]
    model.fit(np.concatenate(bags), np.concatenate([[0], np.cumsum([len(b) for b in bags])]), (got["quality"] > 0).to_numpy(np.float32))
    return model


def score(docs: DataFrame, model: GatedBags, threshold: float = 0.3) -> DataFrame:
    """(doc_id, held_out, score, predicted) for each row of ``docs(doc_id, text)``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in ta.slices(whole, "text"):
                y = model.score(*encode(batch.column("text")))
                yield pa.RecordBatch.from_arrays(
                    [batch.column("doc_id"), batch.column("held_out"), pa.array(y, pa.float64()), pa.array((y >= threshold).astype(np.int32))],
                    names=["doc_id", "held_out", "score", "predicted"],
                )

    rows = ta.whole_texts(docs).select(F.col("doc_id").cast("long").alias("doc_id"), held_out().alias("held_out"), "text")
    return rows.mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def keep_good(docs: DataFrame, model: GatedBags, threshold: float = 0.3) -> DataFrame:
    """The rows of ``docs``, with all their columns, whose text scores at least ``threshold``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in ta.slices(whole, "text"):
                y = model.score(*encode(batch.column("text")))
                yield batch.filter(pa.array(y >= threshold))

    return ta.whole_texts(docs).mapInArrow(run, docs.schema)
