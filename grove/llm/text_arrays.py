"""Whole Arrow text columns as numpy arrays: words, word hashes, shingles.

A column's bytes stay one flat array; every step is a vectorised pass over it, so
no Python object is made per word. Words are maximal runs of bytes other than
space and \\t..\\r; only A-Z are lower-cased. Both rules are ASCII-only and hence
safe on UTF-8 bytes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame



def _give_back() -> None:
    """Let freed large arrays return to the system at once: workers live on between tasks,
    and what the allocator kept would add up to the executor's memory."""
    import ctypes

    libc = ctypes.CDLL(None)
    if hasattr(libc, "mallopt"):
        libc.mallopt(-3, 1 << 20)  # M_MMAP_THRESHOLD
        libc.mallopt(-1, 1 << 20)  # M_TRIM_THRESHOLD
        libc.mallopt(-8, 2)  # M_ARENA_MAX
    pa.set_memory_pool(pa.system_memory_pool())


_give_back()
_rng = np.random.default_rng(20240607)
#: A random odd 64-bit value per byte after lower-casing.
_BYTE = _rng.integers(0, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_BYTE[65:91] = _BYTE[97:123]
_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_BASE_INV = np.uint64(pow(int(_BASE), -1, 2**64))
_SPACE = np.zeros(256, bool)
_SPACE[[32, 9, 10, 11, 12, 13]] = True
_POW: dict[str, np.ndarray] = {}
#: Weights of the five words of a shingle.
_PLACE = _rng.integers(0, 2**63, 8, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
CHUNK_BYTES = 1 << 20
#: Rows of whole texts, and bytes of them, that Spark hands to Python at once.
BATCH_ROWS, BATCH_BYTES = 4000, 2 << 20


def whole_texts(df: DataFrame) -> DataFrame:
    """``df`` in Arrow batches of a bounded number and size of texts (settings of the running session).
    Executors keep the buffers of their largest batches, beside their heap."""
    df.sparkSession.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", BATCH_ROWS)
    df.sparkSession.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", BATCH_BYTES)
    return df


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (public domain splitmix constants)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if "up" not in _POW or len(_POW["up"]) < n:
        size = max(n, CHUNK_BYTES + 1)
        for key, base in (("up", _BASE), ("down", _BASE_INV)):
            a = np.full(size, base, np.uint64)
            a[0] = 1
            _POW[key] = np.cumprod(a, dtype=np.uint64)
    up, down = _POW["up"][:n], _POW["down"][:n]
    if n > 4 * CHUNK_BYTES:  # a single very long text: don't keep its tables
        _POW.clear()
    return up, down


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets of rows + 1) of a string column; null counts as empty."""
    column = column.cast(pa.large_string()).fill_null("")
    n = len(column)
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offs = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + n + 1]
    data = column.buffers()[2]
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[offs[0] : offs[-1]], offs - offs[0]


def slices(batch: pa.RecordBatch, column: str, limit: int = CHUNK_BYTES) -> Iterator[pa.RecordBatch]:
    """The batch in pieces of about ``limit`` text bytes, a row never split."""
    sizes = pc.binary_length(batch.column(column)).fill_null(0).to_numpy(zero_copy_only=False)
    offs = np.concatenate([[0], np.cumsum(sizes, dtype=np.int64)])
    start = 0
    while start < batch.num_rows:
        stop = int(np.searchsorted(offs, offs[start] + limit, "right")) - 1
        stop = min(max(stop, start + 1), batch.num_rows)
        yield batch.slice(start, stop - start)
        start = stop


def words(raw: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, first): byte spans of the words, and per row + 1 its first word's index."""
    n = len(raw)
    if n == 0:
        z = np.zeros(0, np.int64)
        return z, z, np.zeros(len(offs), np.int64)
    word = ~_SPACE[raw]
    begins = word.copy()
    begins[1:] &= ~word[:-1]
    edge = offs[:-1][offs[:-1] < n]
    begins[edge] = word[edge]
    start = np.flatnonzero(begins)
    ends = word.copy()
    ends[:-1] &= ~word[1:]
    last = offs[1:] - 1
    last = last[last >= 0]
    ends[last] = word[last]
    end = np.flatnonzero(ends) + 1
    return start, end, np.searchsorted(start, offs)


def word_hashes(raw: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit hash of each lower-cased word, the same wherever the word stands."""
    if len(start) == 0:
        return np.zeros(0, np.uint64)
    up, down = _powers(len(raw) + 1)
    sums = np.empty(len(raw) + 1, np.uint64)
    sums[0] = 0
    np.cumsum(_BYTE[raw] * up[:-1], out=sums[1:])
    h = (sums[end] - sums[start]) * down[start]
    return mix(h + (end - start).astype(np.uint64) * _PLACE[7])


def shingle_hashes(hashes: np.ndarray, first: np.ndarray, width: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """(hash, row) of each run of ``width`` words; a shorter row gives its whole word run."""
    n_words = np.diff(first)
    rows = len(n_words)
    n = len(hashes)
    parts, owners = [], []
    row_of = np.repeat(np.arange(rows), n_words)
    if n >= width:
        acc = np.zeros(n - width + 1, np.uint64)
        for k in range(width):
            acc += hashes[k : n - width + 1 + k] * _PLACE[k]
        keep = row_of[: n - width + 1] == row_of[width - 1 :]
        parts.append(mix(acc[keep]))
        owners.append(row_of[: n - width + 1][keep])
    short = np.flatnonzero((n_words > 0) & (n_words < width))
    if len(short):
        acc = n_words[short].astype(np.uint64) * _PLACE[6]
        for k in range(width - 1):
            has = n_words[short] > k
            acc[has] += hashes[first[short[has]] + k] * _PLACE[k]
        parts.append(mix(acc))
        owners.append(short)
    if not parts:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    h, o = np.concatenate(parts), np.concatenate(owners)
    order = np.argsort(o, kind="stable")
    return h[order], o[order]


def distinct_by_row(h: np.ndarray, row: np.ndarray, rows: int) -> tuple[np.ndarray, np.ndarray]:
    """(sorted distinct values, offsets of rows + 1)."""
    cuts = np.searchsorted(row, np.arange(rows + 1))
    out = [np.unique(h[a:b]) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
    sizes = np.fromiter((len(x) for x in out), np.int64, rows)
    return (np.concatenate(out) if out else np.zeros(0, np.uint64)), np.concatenate([[0], np.cumsum(sizes)])
