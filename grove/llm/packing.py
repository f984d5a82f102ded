"""Packing documents into fixed-length token sequences.

Documents are tokenised, closed with an end id and cut into pieces of at most the
sequence length. Pieces are dealt at random into groups of bounded size; each group
packs its own by first-fit decreasing, the first bin with room found in a
tournament tree over the bins' free space (O(log bins) a piece). Groups are
independent, so the operator scales out and a lost executor costs only its groups.

Tokens are found once per distinct word of a block of text and then gathered: white
space always separates tokens of a word-level BPE, so a word's ids do not depend on
its neighbours.

Defined results: null text is empty; an empty document is one piece, its end id;
repeated rows are packed each; an empty table gives an empty result.
"""

from __future__ import annotations

import unicodedata
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from grove.llm import text_arrays as ta
from grove.session import cut

_MARK = "\x01"
#: Text that shares one table of distinct words.
BLOCK_BYTES = 16 << 20
#: Text of a block that is split into words at once; of a part only its words' numbers stay.
SPLIT_BYTES = 2 << 20
#: Pieces that a group hands back at once: an executor keeps buffers as large as its largest batch.
OUT_ROWS = 256
_LOADED: dict[str, tuple] = {}


def _tokenizer(path: str) -> tuple:
    """The tokenizer without its own normaliser (done here on whole blocks), and the id of the mark."""
    if path not in _LOADED:
        bare = _load(path)
        bare.normalizer = None
        mark = bare.encode(_MARK, add_special_tokens=False).ids
        assert len(mark) == 1
        _LOADED[path] = (bare, mark[0])
    return _LOADED[path]


def _load(path: str):
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    loaded = Tokenizer.from_file(path)
    loaded.encode_special_tokens = True
    return loaded


def _narrow(path: str, end_id: int) -> str:
    """The type ids travel in: 16 bits if the vocabulary fits."""
    return "<u2" if max(end_id, _tokenizer(path)[0].get_vocab_size()) <= 1 << 16 else "<u4"


def word_ids(words: list[str], path: str) -> tuple[np.ndarray, np.ndarray]:
    """(ids of all words in a row, number of ids of each)."""
    bare, mark = _tokenizer(path)
    odd = [i for i, w in enumerate(words) if _MARK in w]
    plain = words if not odd else ["" if _MARK in w else w for w in words]
    blocks = []
    for k in range(0, len(plain), 64):
        text = f" {_MARK} ".join(plain[k : k + 64]) + f" {_MARK}"
        text = unicodedata.normalize("NFC", text)
        blocks.append(text.replace("Σ", "σ").lower())
    parts = []
    for k in range(0, len(blocks), 256):  # an encoding is far larger than its ids
        parts += [np.array(e.ids, np.uint32) for e in bare.encode_batch_fast(blocks[k : k + 256], add_special_tokens=False)]
    flat = np.concatenate(parts) if parts else np.zeros(0, np.uint32)
    at = np.flatnonzero(flat == mark)
    sizes = np.diff(at, prepend=-1) - 1
    ids = np.delete(flat, at)
    if odd:
        cuts, full = np.split(ids, np.cumsum(sizes)[:-1]), _load(path)
        for i in odd:
            cuts[i] = np.array(full.encode(words[i], add_special_tokens=False).ids, np.uint32)
        sizes = np.array([len(c) for c in cuts])
        ids = np.concatenate(cuts)
    assert len(sizes) == len(words)
    return ids, sizes


def encode_column(column: pa.Array, path: str, end_id: int | None) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, ids, offsets) for consecutive runs of rows."""
    if len(column) == 0:
        return
    parts, counts = [], []
    for part in ta.slices(pa.RecordBatch.from_arrays([column], ["text"]), "text", SPLIT_BYTES):
        lists = pc.ascii_split_whitespace(part.column("text").cast(pa.large_string()).fill_null(""))
        parts.append(lists.flatten().dictionary_encode())
        counts.append(np.diff(lists.offsets.to_numpy()))
    del lists
    parts = pa.chunked_array(parts).unify_dictionaries().chunks
    low = pc.ascii_lower(parts[0].dictionary).dictionary_encode()  # the tokenizer lower-cases
    ids, sizes = word_ids(low.dictionary.to_pylist(), path)
    begin = np.concatenate([[0], np.cumsum(sizes)[:-1]]) if len(sizes) else np.zeros(0, np.int64)
    number = low.indices.to_numpy(zero_copy_only=False)
    code = np.concatenate([number[x.indices.to_numpy(zero_copy_only=False)] for x in parts])
    del parts, low
    offs = np.concatenate([[0], np.cumsum(np.concatenate(counts), dtype=np.int64)])
    row = 0
    while row < len(column):
        stop = max(row + 1, int(np.searchsorted(offs, offs[row] + 500_000, "right")) - 1)
        stop = min(stop, len(column))
        mine = code[offs[row] : offs[stop]]
        n = sizes[mine]
        ends = np.cumsum(n)
        at = np.repeat(begin[mine] - (ends - n), n) + np.arange(ends[-1] if len(ends) else 0)
        flat = ids[at]
        per = np.concatenate([[0], ends])[offs[row : stop + 1] - offs[row]]
        if end_id is not None:
            flat = np.insert(flat, per[1:], end_id)
            per = per + np.arange(len(per))
        yield row, flat.astype("<u4", copy=False), per
        row = stop


def _merged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Batches put together up to a block's size: the more text, the fewer distinct words in all."""
    held: list[pa.RecordBatch] = []
    size = 0

    def whole() -> list[pa.RecordBatch]:
        out = pa.Table.from_batches(held).combine_chunks().to_batches()
        held.clear()  # the parts go before the block is worked on
        return out

    for b in batches:
        held.append(b)
        size += b.column("text").nbytes
        del b
        if size >= BLOCK_BYTES * 3 // 4:
            size = 0
            yield from whole()
    if held:
        yield from whole()


def _pieces(batches: Iterator[pa.RecordBatch], path: str, end_id: int, length: int, keep_ids: bool) -> Iterator[pa.RecordBatch]:
    seen, narrow = 0, _narrow(path, end_id)
    for whole in _merged(batches):
        for batch in ta.slices(whole, "text", BLOCK_BYTES):
            doc = batch.column("doc_id")
            for row, ids, per in encode_column(batch.column("text"), path, end_id):
                total = np.diff(per)
                count = -(-total // length)
                owner = np.repeat(np.arange(len(total)), count)
                start = (np.arange(len(owner)) - np.repeat(np.cumsum(count) - count, count)) * length
                size = np.minimum(total[owner] - start, length)
                raw = memoryview(ids.tobytes())
                spans = [raw[4 * a : 4 * (a + n)] for a, n in zip((per[owner] + start).tolist(), size.tolist(), strict=True)]
                crc = [zlib.crc32(s) for s in spans]
                deal = ta.mix(np.arange(seen, seen + len(owner), dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.array(crc, np.uint64))
                seen += len(owner)
                cols = {
                    "doc_id": doc.take(pa.array(row + owner)),
                    "start": pa.array(start),
                    "length": pa.array(size),
                    "ids_crc32": pa.array(crc, pa.int64()),
                    "doc_tokens": pa.array(total[owner]),
                    "deal": pa.array(deal.view(np.int64)),
                }
                if keep_ids:
                    kept = memoryview(ids.astype(narrow).tobytes())
                    w = np.dtype(narrow).itemsize
                    cols["ids"] = pa.array([bytes(kept[w * a : w * (a + n)]) for a, n in zip((per[owner] + start).tolist(), size.tolist(), strict=True)], pa.binary())
                yield pa.RecordBatch.from_pydict(cols)


class BinTree:
    """Tournament tree of free space: each node holds the most of its two below."""

    def __init__(self, bins: int, capacity: int):
        self.width = 1 << max(0, (bins - 1).bit_length())
        self.most = [capacity] * (2 * self.width)

    def place(self, size: int) -> tuple[int, int]:
        """(bin, offset in it) of the first bin with room, which is then less free."""
        most, node = self.most, 1
        while node < self.width:
            node *= 2
            if most[node] < size:
                node += 1
        free = most[node]
        most[node] = free - size
        leaf = node
        while node > 1:
            node //= 2
            most[node] = max(most[2 * node], most[2 * node + 1])
        return leaf - self.width, free


def first_fit_decreasing(sizes: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """(bin, offset) of each item, items already in falling order of size."""
    tree = BinTree(max(1, len(sizes)), capacity)
    where = np.empty(len(sizes), np.int64)
    offset = np.empty(len(sizes), np.int64)
    for i, n in enumerate(sizes.tolist()):
        where[i], free = tree.place(n)
        offset[i] = capacity - free
    return where, offset


def _pack_group(t: pa.Table, capacity: int, narrow: str) -> pa.Table:
    t = t.combine_chunks()
    order = pc.sort_indices(t, [("length", "descending"), ("doc_id", "ascending"), ("start", "ascending"), ("deal", "ascending")])
    where, offset = first_fit_decreasing(t.column("length").take(order).to_numpy(), capacity)
    first = t.column("grp")[0].as_py() << 24
    keep = [c for c in t.column_names if c not in ("grp", "deal")]
    out = []
    for k in range(0, len(order), OUT_ROWS):
        part = t.select(keep).take(order[k : k + OUT_ROWS])
        if "ids" in keep:
            wide = [np.frombuffer(x, narrow).astype("<u4").tobytes() for x in part.column("ids").to_pylist()]
            part = part.set_column(keep.index("ids"), "ids", pa.array(wide, pa.binary()))
        out.append(part.append_column("sequence_id", pa.array(first + where[k : k + OUT_ROWS])).append_column("offset", pa.array(offset[k : k + OUT_ROWS])))
    return pa.concat_tables(out)


_SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long"


def pack(docs: DataFrame, tokenizer: str, end_id: int = 2, length: int = 4096, group: int = 8192, keep_ids: bool = False) -> DataFrame:
    """A row per piece of each document of ``docs(doc_id, text)``: where it starts in its
    document, how long it is, and in which sequence at which offset it lies.

    ``keep_ids`` adds the piece's ids as little-endian unsigned 32-bit ``ids``."""
    more, narrow = (", ids binary", _narrow(tokenizer, end_id)) if keep_ids else ("", "<u4")
    pieces = cut(
        ta.whole_texts(docs).select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(
            lambda it: _pieces(it, tokenizer, end_id, length, keep_ids), f"{_SCHEMA}, deal long{more}"
        ),
        "pieces",
    )
    groups = max(1, -(-pieces.count() // group))
    dealt = pieces.withColumn("grp", F.pmod("deal", F.lit(groups)))
    return dealt.groupBy("grp").applyInArrow(lambda t: _pack_group(t, length, narrow), f"{_SCHEMA}{more}, sequence_id long, offset long")


def sequences(packed: DataFrame, length: int = 4096, pad_id: int = 0) -> DataFrame:
    """(sequence_id, tokens, ids): the packed sequences themselves, from pieces with ids.

    A sequence is padded to ``length`` unless its own length is a power of two."""

    def join(t: pa.Table) -> pa.Table:
        t = t.sort_by("offset")
        ids = np.frombuffer(b"".join(t.column("ids").to_pylist()), "<u4")
        n = len(ids)
        full = ids if n & (n - 1) == 0 else np.concatenate([ids, np.full(length - n, pad_id, "<u4")])
        return pa.table({"sequence_id": [t.column("sequence_id")[0].as_py()], "tokens": [n], "ids": [full.astype("<i4").tolist()]}, pa.schema([("sequence_id", pa.int64()), ("tokens", pa.int64()), ("ids", pa.list_(pa.int32()))]))

    return packed.groupBy("sequence_id").applyInArrow(join, "sequence_id long, tokens long, ids array<int>")
