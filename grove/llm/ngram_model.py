"""A trigram language model in a memory-mapped Elias-Fano trie.

Levels. One: the sorted hashes of the vocabulary, with counts; a word's id is its
rank. Two: the words that follow a word, as one monotone sequence of
``context * (V + 1) + word``, with a monotone pointer from each context to its first
successor. Three: under a node of level two, the words that follow it, named by
their rank among the successors of its last word (a small number, hence few bits).
Probabilities and back-off weights are quantised to 16 bits. Each level is cut into
segments by its first key, so builders work on bounded pieces, and readers map
segments on demand: what is resident is what queries touch.

Smoothing. Level one adds a half to each count, with one class for all unknown
words. Levels two and three discount each count by ``DISCOUNT`` and hand the rest,
including all n-grams seen once (which are not stored), to the level below, so every
context's probabilities sum to one.

Counting. Tasks count sorted blocks of keys and send one compressed block a segment;
segments merge them. Trigrams are counted only where both their bigrams are stored,
which loses none that occurs twice. All documents are counted; nothing is sampled.

Defined results: null text is empty and is one end token; an empty training set gives
every word the unknown class with N = 0 and V = 0.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from grove.llm import segments
from grove.llm import text_arrays as ta
from grove.llm.elias_fano import EliasFano
from grove.session import cut, drop_cut, scratch

DISCOUNT = 0.75
#: The end token's place among the hashes.
END = np.uint64(0x2545F4914F6CDD1D)
NONE = np.uint32(0xFFFFFFFF)
_FLUSH = 3_000_000
_STEP = 12.0 / 65535


def quantise(log10: np.ndarray) -> np.ndarray:
    return np.clip(np.rint(-log10 / _STEP), 0, 65535).astype(np.uint16)


def value(code: np.ndarray) -> np.ndarray:
    return -_STEP * code.astype(np.float64)


@dataclass
class Model:
    """Where the segments lie and the sums over all of them; small enough for a closure."""

    folder: str
    parts: int
    total: int = 0  # N
    vocabulary: int = 0  # V
    documents: int = 0
    first_id: list[int] = field(default_factory=list)
    words: list[str] = field(default_factory=list)
    pairs: list[str] = field(default_factory=list)
    first_pair: list[int] = field(default_factory=list)
    triples: list[str | None] = field(default_factory=list)
    fanout: int = 1

    def base(self, count: np.ndarray) -> np.ndarray:
        return np.log10((count + 0.5) / (self.total + 0.5 * (self.vocabulary + 1)))

    def _level(self, names: list, k: int, at: int = 0) -> EliasFano:
        return EliasFano(*segments.maps(self.folder, names[k])[at : at + 4])

    def word_part(self, h: np.ndarray) -> np.ndarray:
        return (((h >> np.uint64(32)) * np.uint64(self.parts)) >> np.uint64(32)).astype(np.int64)

    def look_up(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(id or NONE, count) of sorted distinct hashes."""
        ids, counts = np.full(len(h), NONE, np.uint32), np.zeros(len(h), np.int64)
        cuts = np.searchsorted(self.word_part(h), np.arange(self.parts + 1))
        for k in range(self.parts):
            a, b = cuts[k], cuts[k + 1]
            if a < b and self.words[k]:
                at, there = self._level(self.words, k).find(h[a:b])
                got = np.flatnonzero(there)
                ids[a + got] = at[got] + self.first_id[k]
                counts[a + got] = segments.maps(self.folder, self.words[k])[4][at[got]]
        return ids, counts

    def count_of(self, ids: np.ndarray) -> np.ndarray:
        out = np.empty(len(ids), np.int64)
        part = np.searchsorted(self.first_id, ids, "right") - 1
        for k in np.unique(part):
            own = part == k
            out[own] = segments.maps(self.folder, self.words[k])[4][ids[own] - self.first_id[k]]
        return out

    # level two: contexts 0..V, V being the start of a text
    def context_part(self, ctx: np.ndarray) -> np.ndarray:
        return (ctx * self.parts) // (self.vocabulary + 1)

    def context_range(self, k: int) -> tuple[int, int]:
        v = self.vocabulary + 1
        return -(-k * v // self.parts), -(-(k + 1) * v // self.parts)

    def find_pairs(self, key: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """For sorted distinct keys: (global place or -1, rank among the context's successors, log10
        probability, or the context's back-off weight where the pair isn't stored)."""
        u = np.uint64(self.vocabulary + 1)
        ctx = (key // u).astype(np.int64)
        place, rank, logp = np.full(len(key), -1, np.int64), np.zeros(len(key), np.int64), np.zeros(len(key))
        cuts = np.searchsorted(self.context_part(ctx), np.arange(self.parts + 1))
        for k in range(self.parts):
            a, b = cuts[k], cuts[k + 1]
            if a == b or not self.pairs[k]:
                continue
            raw = segments.maps(self.folder, self.pairs[k])
            first, _ = self.context_range(k)
            own = ctx[a:b] - first
            at, there = EliasFano(*raw[:4]).find(key[a:b] - np.uint64(first) * u)
            logp[a:b] = np.where(there, value(raw[8][np.minimum(at, len(raw[8]) - 1)]) if len(raw[8]) else 0.0, value(raw[9][own]))
            got = np.flatnonzero(there)
            place[a + got] = at[got] + self.first_pair[k]
            rank[a + got] = at[got] - EliasFano(*raw[4:8]).get(own[got]).astype(np.int64)
        return place, rank, logp

    def find_triples(self, place: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(log10 probability where stored, whether stored); else the first is the node's back-off weight."""
        logp, there = np.zeros(len(place)), np.zeros(len(place), bool)
        part = np.searchsorted(self.first_pair, place, "right") - 1
        order = np.argsort(part, kind="stable")
        cuts = np.searchsorted(part[order], np.arange(self.parts + 1))
        for k in range(self.parts):
            own = order[cuts[k] : cuts[k + 1]]
            if len(own) == 0 or not self.triples[k]:
                continue
            raw = segments.maps(self.folder, self.triples[k])
            node = place[own] - self.first_pair[k]
            at, hit = EliasFano(*raw[:4]).find(node.astype(np.uint64) * np.uint64(self.fanout) + np.maximum(rank[own], 0).astype(np.uint64))
            hit &= rank[own] >= 0
            logp[own] = np.where(hit, value(raw[4][np.minimum(at, len(raw[4]) - 1)]) if len(raw[4]) else 0.0, value(raw[5][node]))
            there[own] = hit
        return logp, there


def learns(column: str = "doc_id"):
    """False where crc32 of the id as text leaves 1 on division by 5; true for a null id."""
    return F.coalesce(F.pmod(F.crc32(F.col(column).cast("string").cast("binary")), F.lit(5)) != 1, F.lit(True))


# ---- blocks of sorted keys with counts ----


def _pack(keys: np.ndarray, counts: np.ndarray) -> bytes:
    z = zstandard.ZstdCompressor(level=1)
    gaps = np.diff(keys, prepend=np.uint64(0))
    planes = np.ascontiguousarray(gaps.view(np.uint8).reshape(-1, 8).T).tobytes()
    return z.compress(planes + counts.astype("<u4").tobytes())


def _unpack(block: bytes) -> tuple[np.ndarray, np.ndarray]:
    raw = zstandard.ZstdDecompressor().decompress(block)
    n = len(raw) // 12
    gaps = np.ascontiguousarray(np.frombuffer(raw, np.uint8, 8 * n).reshape(8, n).T).view(np.uint64).ravel()
    return np.cumsum(gaps, dtype=np.uint64), np.frombuffer(raw, "<u4", n, 8 * n).astype(np.int64)


def _merge(blocks: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    got = [_unpack(b) for b in blocks]
    keys, counts = np.concatenate([k for k, _ in got]), np.concatenate([c for _, c in got])
    order = np.argsort(keys, kind="stable")
    keys, counts = keys[order], counts[order]
    first = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
    return keys[first], np.add.reduceat(counts, first)


_BLOCKS = "part int, block binary"


def _blocks(arrays: Iterator[np.ndarray], part_of: Callable[[np.ndarray], np.ndarray], parts: int) -> Iterator[pa.RecordBatch]:
    held: list[np.ndarray] = []
    size = 0

    def flush() -> pa.RecordBatch:
        keys, counts = np.unique(np.concatenate(held), return_counts=True)
        cuts = np.searchsorted(part_of(keys), np.arange(parts + 1))
        some = [k for k in range(parts) if cuts[k] < cuts[k + 1]]
        data = [_pack(keys[cuts[k] : cuts[k + 1]], counts[cuts[k] : cuts[k + 1]]) for k in some]
        return pa.RecordBatch.from_arrays([pa.array(some, pa.int32()), pa.array(data, pa.binary())], names=["part", "block"])

    for a in arrays:
        held.append(a)
        size += len(a)
        if size >= _FLUSH:
            yield flush()
            held, size = [], 0
    if size:
        yield flush()


def _text_hashes(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    """Token hashes of all rows with their end tokens, and offsets of rows + 1."""
    raw, offs = ta.text_bytes(batch.column("text"))
    start, end, first = ta.words(raw, offs)
    h = np.insert(ta.word_hashes(raw, start, end), first[1:], END)
    return h, first + np.arange(len(first))


def _count_words(batches: Iterator[pa.RecordBatch], model: Model) -> Iterator[pa.RecordBatch]:
    yield from _blocks((_text_hashes(b)[0] for whole in batches for b in ta.slices(whole, "text")), model.word_part, model.parts)


def _encode(batches: Iterator[pa.RecordBatch], model: Model) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for b in ta.slices(whole, "text"):
            h, at = _text_hashes(b)
            keys, back = np.unique(h, return_inverse=True)
            ids, counts = model.look_up(keys)
            base = model.base(counts)[back]
            known = (counts > 0)[back]
            tokens = ids[back]
            raw = memoryview(tokens.astype("<u4").tobytes())
            yield pa.RecordBatch.from_arrays(
                [
                    b.column("doc_id"), b.column("learns"), pa.array(np.diff(at)), pa.array(np.add.reduceat(known.astype(np.int64), at[:-1])), pa.array(np.add.reduceat(base, at[:-1])),
                    pa.array([bytes(raw[4 * x : 4 * y]) for x, y in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)], pa.binary()),
                ],
                names=["doc_id", "learns", "n_tokens", "n_known", "base_score", "ids"],
            )


def _id_runs(batches: Iterator[pa.RecordBatch], limit: int = 1_000_000) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """(rows, ids, offsets) of about ``limit`` tokens."""
    for b in batches:
        if b.num_rows == 0:
            continue
        column = b.column("ids").cast(pa.large_binary())
        offs = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1] // 4
        ids = np.frombuffer(column.buffers()[2], "<u4")
        start = 0
        while start < b.num_rows:
            stop = min(b.num_rows, max(start + 1, int(np.searchsorted(offs, offs[start] + limit, "right")) - 1))
            yield b.slice(start, stop - start), ids[offs[start] : offs[stop]], offs[start : stop + 1] - offs[start]
            start = stop


def _pair_keys(ids: np.ndarray, at: np.ndarray, model: Model) -> tuple[np.ndarray, np.ndarray]:
    """(context * (V + 1) + word, whether the context is known) of each token.

    An unknown word stands as V, which no pair has: looked up, it gives its context's back-off weight."""
    v = np.uint64(model.vocabulary)
    before = np.empty(len(ids), np.uint64)
    before[1:] = ids[:-1]
    before[at[:-1]] = v
    return before * (v + np.uint64(1)) + np.where(ids == NONE, v, ids.astype(np.uint64)), before != NONE


def _count_pairs(batches: Iterator[pa.RecordBatch], model: Model) -> Iterator[pa.RecordBatch]:
    u = np.uint64(model.vocabulary + 1)
    keys = (k[ok] for _, ids, at in _id_runs(batches) for k, ok in [_pair_keys(ids, at, model)])
    yield from _blocks(keys, lambda x: model.context_part((x // u).astype(np.int64)), model.parts)


def _pair_places(ids: np.ndarray, at: np.ndarray, model: Model) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(known, place, rank, log10 probability or weight) of each token's pair."""
    key, known = _pair_keys(ids, at, model)
    keys, back = np.unique(key[known], return_inverse=True)
    place, rank, logp = np.full(len(ids), -1, np.int64), np.full(len(ids), -1, np.int64), np.zeros(len(ids))
    p, r, g = model.find_pairs(keys)
    r = np.where(p >= 0, r, -1)
    place[known], rank[known], logp[known] = p[back], r[back], g[back]
    return known, place, rank, logp


def _inside(at: np.ndarray, n: int) -> np.ndarray:
    """Tokens with another token of their text before them."""
    out = np.ones(n, bool)
    out[at[:-1]] = False
    return out


def _count_triples(batches: Iterator[pa.RecordBatch], model: Model) -> Iterator[pa.RecordBatch]:
    fan = np.uint64(model.fanout)

    def keys() -> Iterator[np.ndarray]:
        for _, ids, at in _id_runs(batches):
            _, place, rank, _ = _pair_places(ids, at, model)
            here = np.flatnonzero(_inside(at, len(ids)))
            here = here[(place[here] >= 0) & (place[here - 1] >= 0)]
            yield place[here - 1].astype(np.uint64) * fan + rank[here].astype(np.uint64)

    yield from _blocks(keys(), lambda x: np.searchsorted(model.first_pair, (x // fan).astype(np.int64), "right") - 1, model.parts)


def _save_words(t: pa.Table, model: Model) -> pa.Table:
    keys, counts = _merge(t.column("block").to_pylist())
    name = segments.put(model.folder, [*EliasFano.build(keys, 2**64).arrays(), counts])
    return pa.table({"part": pa.array([t.column("part")[0].as_py()], pa.int32()), "name": [name], "n": [len(keys)], "mass": [int(counts.sum())]})


def _save_pairs(t: pa.Table, model: Model) -> pa.Table:
    part = t.column("part")[0].as_py()
    keys, counts = _merge(t.column("block").to_pylist())
    u = np.uint64(model.vocabulary + 1)
    first, last = model.context_range(part)
    keep = counts >= 2
    keys, counts = keys[keep], counts[keep]
    ctx = (keys // u).astype(np.int64)
    word = (keys % u).astype(np.int64)
    mass = np.empty(last - first, np.int64)
    real = min(last, model.vocabulary)
    mass[: real - first] = model.count_of(np.arange(first, real))
    if last > model.vocabulary:
        mass[-1] = model.documents
    own = ctx - first
    kept = np.bincount(own, counts - DISCOUNT, minlength=last - first) if len(own) else np.zeros(last - first)
    rest = np.clip(1 - kept / np.maximum(mass, 1), 1e-12, 1)
    p = (counts - DISCOUNT) / mass[own] + rest[own] * 10 ** model.base(model.count_of(word)) if len(own) else np.zeros(0)
    starts = np.searchsorted(own, np.arange(last - first + 1)).astype(np.uint64)
    name = segments.put(
        model.folder,
        [
            *EliasFano.build(keys - np.uint64(first) * u, (last - first) * int(u)).arrays(), *EliasFano.build(starts, len(keys) + 1).arrays(),
            quantise(np.log10(p)), quantise(np.log10(rest)), counts, word.astype(np.int64),
        ],
    )
    fan = int(np.bincount(own).max()) if len(own) else 0
    return pa.table({"part": pa.array([part], pa.int32()), "name": [name], "n": [len(keys)], "mass": [fan]})


def _save_triples(t: pa.Table, model: Model) -> pa.Table:
    part = t.column("part")[0].as_py()
    keys, counts = _merge(t.column("block").to_pylist())
    keep = counts >= 2
    keys, counts = keys[keep], counts[keep]
    fan = np.uint64(model.fanout)
    raw = segments.maps(model.folder, model.pairs[part])
    size = len(raw[8])
    node = (keys // fan).astype(np.int64) - model.first_pair[part]
    rank = (keys % fan).astype(np.int64)
    mass, middle = raw[10][node], raw[11][node]
    lower = np.zeros(len(keys))
    where = model.context_part(middle)
    for k in np.unique(where):
        own = np.flatnonzero(where == k)
        other = segments.maps(model.folder, model.pairs[k])
        begin = EliasFano(*other[4:8]).get(middle[own] - model.context_range(k)[0]).astype(np.int64)
        lower[own] = value(other[8][begin + rank[own]])
    kept = np.bincount(node, counts - DISCOUNT, minlength=size) if len(node) else np.zeros(size)
    rest = np.clip(1 - kept / raw[10], 1e-12, 1)
    p = (counts - DISCOUNT) / mass + rest[node] * 10**lower
    name = segments.put(model.folder, [*EliasFano.build(keys - np.uint64(model.first_pair[part]) * fan, max(1, size) * model.fanout).arrays(), quantise(np.log10(p)), quantise(np.log10(rest))])
    return pa.table({"part": pa.array([part], pa.int32()), "name": [name], "n": [len(keys)], "mass": [int(counts.sum())]})


_SAVED = "part int, name string, n long, mass long"


def _built(blocks: DataFrame, save: Callable, model: Model) -> list:
    rows = cut(blocks.groupBy("part").applyInArrow(lambda t: save(t, model), _SAVED), "level").collect()  # one row a segment
    by = {r.part: r for r in rows}
    return [by.get(k) for k in range(model.parts)]


def train(docs: DataFrame, documents_per_part: int = 16384, most_parts: int = 4096) -> tuple[Model, DataFrame]:
    """A model from the rows of ``docs(doc_id, text, learns)`` that it may learn from, and all rows encoded."""
    spark = docs.sparkSession
    model = Model(scratch(spark, "ngrams"), min(most_parts, max(1, -(-docs.count() // documents_per_part))))
    saved = _built(docs.where("learns").select("text").mapInArrow(lambda it: _count_words(it, model), _BLOCKS), _save_words, model)
    model.words = [r.name if r else "" for r in saved]
    sizes = [r.n if r else 0 for r in saved]
    model.first_id = [0, *np.cumsum(sizes).tolist()][:-1]
    model.vocabulary, model.total = sum(sizes), sum(r.mass for r in saved if r)
    if model.vocabulary >= int(NONE):
        raise ValueError("more than 2^32 - 2 distinct words")
    encoded = cut(docs.select("doc_id", "learns", "text").mapInArrow(lambda it: _encode(it, model), "doc_id long, learns boolean, n_tokens long, n_known long, base_score double, ids binary"), "encoded")
    learnt = encoded.where("learns").select("ids")
    model.documents = learnt.count()
    saved = _built(learnt.mapInArrow(lambda it: _count_pairs(it, model), _BLOCKS), _save_pairs, model)
    model.pairs = [r.name if r else "" for r in saved]
    sizes = [r.n if r else 0 for r in saved]
    model.first_pair = [0, *np.cumsum(sizes).tolist()][:-1]
    model.fanout = max(1, *[r.mass if r else 0 for r in saved]) if saved else 1
    saved = _built(learnt.mapInArrow(lambda it: _count_triples(it, model), _BLOCKS), _save_triples, model)
    model.triples = [r.name if r else None for r in saved]
    return model, encoded


def log10_tokens(ids: np.ndarray, at: np.ndarray, model: Model, unigram: np.ndarray) -> np.ndarray:
    """log10 probability of each token given the two before it."""
    known, place, rank, logp = _pair_places(ids, at, model)
    two = np.where(place >= 0, logp, logp + unigram)
    inside = _inside(at, len(ids))
    here = np.flatnonzero(inside)
    here = here[place[here - 1] >= 0]
    three, hit = model.find_triples(place[here - 1], rank[here])
    out = two
    out[here] = np.where(hit, three, three + two[here])
    return out


def _score(batches: Iterator[pa.RecordBatch], model: Model) -> Iterator[pa.RecordBatch]:
    for b, ids, at in _id_runs(batches):
        one = np.full(len(ids), model.base(np.zeros(1))[0])
        known = ids != NONE
        keys, back = np.unique(ids[known], return_inverse=True)
        one[known] = value(quantise(model.base(model.count_of(keys.astype(np.int64)))))[back]
        total = np.add.reduceat(log10_tokens(ids, at, model, one), at[:-1])
        names = ["doc_id", "learns", "n_tokens", "n_known", "base_score"]
        yield pa.RecordBatch.from_arrays([b.column(c) for c in names] + [pa.array(total)], names=[*names, "score"])


def score(encoded: DataFrame, model: Model) -> DataFrame:
    """(doc_id, learns, n_tokens, n_known, base_score, score) of each encoded row."""
    return encoded.mapInArrow(lambda it: _score(it, model), "doc_id long, learns boolean, n_tokens long, n_known long, base_score double, score double")


def score_documents(docs: DataFrame) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score) of each row of docs(doc_id, text)."""
    rows = ta.whole_texts(docs).select(F.col("doc_id").cast("long").alias("doc_id"), "text", learns().alias("learns"))
    model, encoded = train(rows)
    out = cut(score(encoded, model), "scored")
    drop_cut(encoded)
    return out.select("doc_id", (~F.col("learns")).alias("held_out"), "n_tokens", "n_known", F.lit(model.total).cast("long").alias("train_tokens"), "base_score", "score")
