"""Near-duplicate documents by min-max hashing.

Every permutation of the shingle hashes gives two signature values, its minimum and
its maximum; a value agrees between two documents with probability equal to their
Jaccard similarity, and the pair is negatively correlated, so half as many hash
evaluations give a signature of no larger variance. Bands of the signature name
buckets; what shares a bucket is narrowed by the signature and then confirmed on
whole shingle sets.

Shape of the computation, chosen so that no group is ever held whole or expanded
into pairs:

1. one pass over the texts gives each document the digest of its set and its
   signature; equal digests are one class (an aggregation), only its least id goes on;
2. classes are linked to loose clusters inside each bucket, where the signature
   says the similarity may reach ``loose``; a bucket over ``block`` members is dealt
   to blocks, and a task returns a forest, never pairs;
3. inside each loose cluster, dealt in the same way by shingle count, whole sets
   are compared by a flood over an inverted index, which finds the exact components
   of the threshold graph and again returns a forest.

A group of many blocks is linked in two passes. In the first each block has its own
members and ``ANCHORS`` of the group's, the same for all blocks, so that a group of near
copies falls together. In the second only members outside the group's largest
component go to every block: two members of one component need no comparison. So a
group of n near copies costs about n rows, and no link is lost whatever the group is.

With 20 bands of 5 values a pair at similarity 0.85 shares no bucket with
probability 8e-6; ``loose`` lies four standard errors below the threshold.

Defined results: null or empty text has an empty set and no links; rows with the
same id are one node; a row with a null id is linked with nothing, its
``component_id`` is null and it is kept.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from grove.llm import text_arrays as ta
from grove.operators.components import star_components
from grove.session import cut, drop_cut

BANDS, ROWS = 20, 5
#: Members of a large group that each of its blocks has.
ANCHORS = 64
#: Ids that are broadcast, once counted, to meet the texts; more of them meet by a shuffle.
BROADCAST_IDS = 2_000_000
_PERMS = BANDS * ROWS // 2
_rng = np.random.default_rng(77)
_MUL = (_rng.integers(0, 2**31, _PERMS, dtype=np.uint32) * np.uint32(2)) + np.uint32(1)
_ADD = _rng.integers(0, 2**32, _PERMS, dtype=np.uint32)
#: Values are laid out so that a minimum and a maximum of one permutation never share a band.
_ORDER = np.concatenate([np.arange(0, _PERMS), np.arange(_PERMS, 2 * _PERMS)])


def _i64(x: np.ndarray) -> pa.Array:
    return pa.array(x.view(np.int64) if x.dtype == np.uint64 else x, pa.int64())


def signature(h: np.ndarray, offs: np.ndarray) -> np.ndarray:
    """(rows, 2 * permutations) uint32; rows without a shingle are all zero."""
    rows = len(offs) - 1
    out = np.zeros((rows, 2 * _PERMS), np.uint32)
    full = np.flatnonzero(np.diff(offs) > 0)
    if len(full) == 0:
        return out
    x = (h >> np.uint64(32)).astype(np.uint32)
    at = offs[full]
    for k in range(_PERMS):
        y = x * _MUL[k] + _ADD[k]
        out[full, k] = np.minimum.reduceat(y, at)
        out[full, _PERMS + k] = np.maximum.reduceat(y, at)
    return out[:, _ORDER]


def band_keys(sig: np.ndarray) -> np.ndarray:
    """(rows, bands) uint64."""
    s = sig.reshape(len(sig), BANDS, ROWS).astype(np.uint64)
    acc = np.zeros((len(sig), BANDS), np.uint64)
    for k in range(ROWS):
        acc = ta.mix(acc * np.uint64(0x100000001B3) + s[:, :, k] + np.uint64(k + 1))
    return acc + np.arange(BANDS, dtype=np.uint64)


def _sign(batches: Iterator[pa.RecordBatch], width: int) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for batch in ta.slices(whole, "text"):
            raw, offs = ta.text_bytes(batch.column("text"))
            start, end, first = ta.words(raw, offs)
            h, row = ta.shingle_hashes(ta.word_hashes(raw, start, end), first, width)
            h, at = ta.distinct_by_row(h, row, batch.num_rows)
            sums = np.concatenate([[np.uint64(0)], np.cumsum(h, dtype=np.uint64)])
            other = np.concatenate([[np.uint64(0)], np.cumsum(ta.mix(h ^ np.uint64(0x5851F42D4C957F2D)), dtype=np.uint64)])
            sig = signature(h, at)
            keys = band_keys(sig)
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column("doc_id"),
                    pa.array(np.diff(at)),
                    _i64(sums[at[1:]] - sums[at[:-1]]),
                    _i64(other[at[1:]] - other[at[:-1]]),
                    pa.ListArray.from_arrays(pa.array(np.arange(0, keys.size + 1, BANDS, dtype=np.int32)), _i64(keys.ravel())),
                    pa.array([r.tobytes() for r in sig.astype(np.uint8)], pa.binary()),
                ],
                names=["doc_id", "n_shingles", "d1", "d2", "bands", "sketch"],
            )


def _sets(batches: Iterator[pa.RecordBatch], width: int) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for batch in ta.slices(whole, "text"):
            raw, offs = ta.text_bytes(batch.column("text"))
            start, end, first = ta.words(raw, offs)
            h, row = ta.shingle_hashes(ta.word_hashes(raw, start, end), first, width)
            h, at = ta.distinct_by_row(h, row, batch.num_rows)
            yield pa.RecordBatch.from_arrays(
                [batch.column(c) for c in batch.schema.names if c != "text"] + [pa.array([h[a:b].tobytes() for a, b in zip(at[:-1], at[1:], strict=True)], pa.binary())],
                names=[c for c in batch.schema.names if c != "text"] + ["shingles"],
            )


def _groups(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[pa.Table]:
    """Runs of whole groups from a stream that is sorted by ``keys``."""
    held: list[pa.RecordBatch] = []

    def last_cut(t: pa.Table) -> int:
        cols = [t.column(k).to_numpy() for k in keys]
        same = np.ones(t.num_rows, bool)
        for c in cols:
            same &= c == c[-1]
        return t.num_rows - int(np.argmin(same[::-1])) if not same.all() else 0

    for b in batches:
        if b.num_rows == 0:
            continue
        held.append(b)
        t = pa.Table.from_batches(held)
        k = last_cut(t)
        if k:
            yield t.slice(0, k).combine_chunks()
            held = t.slice(k).combine_chunks().to_batches()
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def _bounds(t: pa.Table, keys: list[str]) -> np.ndarray:
    change = np.zeros(t.num_rows, bool)
    change[0] = True
    for k in keys:
        c = t.column(k).to_numpy()
        change[1:] |= c[1:] != c[:-1]
    return np.append(np.flatnonzero(change), t.num_rows)


def _forest(pairs: np.ndarray) -> np.ndarray:
    """A spanning forest of index pairs, by union-find."""
    up: dict[int, int] = {}

    def find(x: int) -> int:
        while up.get(x, x) != x:
            up[x] = up.get(up[x], up[x])
            x = up[x]
        return x

    keep = []
    for n, (a, b) in enumerate(pairs.tolist()):
        a, b = find(a), find(b)
        if a != b:
            up[max(a, b)] = min(a, b)
            keep.append(n)
    return pairs[keep]


def _loose(batches: Iterator[pa.RecordBatch], loose: float) -> Iterator[pa.RecordBatch]:
    """Links inside buckets whose signatures agree in at least ``loose`` of their values."""
    need = int(np.floor(loose * 2 * _PERMS))
    for t in _groups(batches, ["key", "part"]):
        at = _bounds(t, ["key", "part"])
        rep = t.column("rep").to_numpy()
        sk = np.frombuffer(b"".join(t.column("sketch").to_pylist()), np.uint8).reshape(len(rep), -1)
        size = np.diff(at)
        group = np.repeat(np.arange(len(size)), size)
        found = []
        small = size[group] <= 8
        for d in range(1, 8):
            i = np.flatnonzero(small[:-d] & (group[:-d] == group[d:])) if len(rep) > d else np.zeros(0, np.int64)
            if len(i):
                ok = i[(sk[i] == sk[i + d]).sum(1) >= need]
                found.append(np.stack([ok, ok + d], 1))
        for g in np.flatnonzero(size > 8):
            left = np.arange(at[g], at[g + 1])
            while len(left):
                queue, left = [left[0]], left[1:]
                while queue and len(left):
                    x = queue.pop()
                    hit = (sk[left] == sk[x]).sum(1) >= need
                    new = left[hit]
                    if len(new):
                        found.append(np.stack([np.full(len(new), x), new], 1))
                        queue.extend(new.tolist())
                        left = left[~hit]
        if found:
            e = _forest(np.concatenate(found))
            yield pa.RecordBatch.from_arrays([pa.array(rep[e[:, 0]]), pa.array(rep[e[:, 1]])], names=["src", "dst"])


def flood(sets: list[np.ndarray], percent: int) -> list[tuple[int, int]]:
    """A spanning forest of the graph that links sets with
    100 * intersection >= percent * union; exact."""
    n = len(sets)
    size = np.array([len(s) for s in sets])
    every = np.concatenate(sets)
    owner = np.repeat(np.arange(n), size)
    values, code = np.unique(every, return_inverse=True)
    order = np.argsort(code, kind="stable")
    posting = owner[order]
    cuts = np.searchsorted(code[order], np.arange(len(values) + 1))
    starts = np.concatenate([[0], np.cumsum(size)])
    free = np.ones(n, bool)
    out = []
    for seed in range(n):
        if not free[seed]:
            continue
        free[seed] = False
        queue = [seed]
        while queue:
            x = queue.pop()
            mine = code[starts[x] : starts[x + 1]]
            lens = cuts[mine + 1] - cuts[mine]
            at = np.repeat(cuts[mine] - np.concatenate([[0], np.cumsum(lens)[:-1]]), lens) + np.arange(lens.sum())
            common = np.bincount(posting[at], minlength=n)
            new = np.flatnonzero(free & (100 * common >= percent * (size[x] + size - common)))
            free[new] = False
            out.extend((x, int(y)) for y in new)
            queue.extend(new.tolist())
    return out


def _strict(batches: Iterator[pa.RecordBatch], percent: int) -> Iterator[pa.RecordBatch]:
    for t in _groups(batches, ["cluster", "part"]):
        at = _bounds(t, ["cluster", "part"])
        rep = t.column("rep").to_numpy()
        sets = [np.frombuffer(x, np.uint64) for x in t.column("shingles").to_pylist()]
        e = [(a + i, a + j) for a, b in zip(at[:-1], at[1:], strict=True) if b - a > 1 for i, j in flood(sets[a:b], percent)]
        if e:
            e = np.array(e)
            yield pa.RecordBatch.from_arrays([pa.array(rep[e[:, 0]]), pa.array(rep[e[:, 1]])], names=["src", "dst"])


def _dealt(df: DataFrame, everywhere: Column) -> DataFrame:
    """Rows of a group of ``blocks`` blocks: each in its own block, those ``everywhere`` in all of them."""
    mine = F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int")
    return df.withColumn("part", F.explode(F.when((F.col("blocks") > 1) & everywhere, F.sequence(F.lit(0), F.col("blocks") - 1)).otherwise(F.array(mine))))


def _linked(members: DataFrame, group: str, find: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> DataFrame:
    """(src, dst): links that join what ``find`` would join within the groups of members(rep, group, blocks, n, ...)."""
    tasks = int(members.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def run(df: DataFrame) -> DataFrame:
        return df.drop("blocks", "n").repartition(tasks, group, "part").sortWithinPartitions(group, "part").mapInArrow(find, "src long, dst long")

    anchor = F.pmod(F.xxhash64("rep", F.lit(1)), F.col("n")) < ANCHORS
    first = cut(run(_dealt(members, anchor)), "links")
    large = members.where("blocks > 1")
    if large.limit(1).count() == 0:
        return first
    joined = star_components(first)
    of = large.join(joined.withColumnRenamed("v", "rep"), "rep", "left").withColumn("leader", F.coalesce("leader", "rep"))
    sizes = of.groupBy(group, "leader").agg(F.count("*").alias("size"), F.first("n").alias("n"))
    main = sizes.groupBy(group).agg(F.max(F.struct("size", "leader")).alias("most"), F.first("n").alias("n")).where("most.size < n").select(group, F.col("most.leader").alias("main"))
    rest = _dealt(of.join(main, group), F.col("leader") != F.col("main")).drop("leader", "main")
    return first.unionByName(cut(run(rest), "links"))


def _few(ids: DataFrame) -> DataFrame:
    """The written table ``ids``, with a hint to broadcast if its rows are counted to be few:
    a plan's own guess of its size would shuffle every text to meet them."""
    return F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids


def near_duplicates(
    docs: DataFrame, percent: int = 85, width: int = 5, loose: float | None = None, block: int = 1024, block_shingles: int = 2_000_000
) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for each row of ``docs(doc_id, text)``.

    Documents are linked when 100 * |A and B| >= percent * |A or B| on their sets of
    ``width``-word shingles; ``component_id`` is the least id reachable.
    """
    loose = loose if loose is not None else percent / 100 - 0.15
    rows = ta.whole_texts(docs).select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    signed = cut(
        rows.mapInArrow(lambda it: _sign(it, width), "doc_id long, n_shingles long, d1 long, d2 long, bands array<long>, sketch binary"),
        "signed",
    )
    named = signed.where("doc_id is not null and n_shingles > 0")
    classes = cut(
        named.groupBy("d1", "d2", "n_shingles").agg(F.min("doc_id").alias("rep"), F.first("bands").alias("bands"), F.first("sketch").alias("sketch")),
        "classes",
    )
    same = named.join(classes.select("d1", "d2", "n_shingles", "rep"), ["d1", "d2", "n_shingles"]).where("doc_id <> rep").select(F.col("doc_id").alias("src"), F.col("rep").alias("dst"))

    exploded = classes.select("rep", F.explode("bands").alias("key"))
    shared = exploded.groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
    member = exploded.join(shared, "key").select("rep", "key", "n", F.ceil(F.col("n") / block).cast("int").alias("blocks"))
    linked = _linked(member.join(classes.select("rep", "sketch"), "rep"), "key", lambda it: _loose(it, loose))
    clusters = cut(star_components(linked), "clusters")
    texts = rows.join(_few(clusters.select(F.col("v").alias("doc_id"), F.col("leader").alias("cluster"))), "doc_id").select("doc_id", "cluster", "text")
    sets = cut(texts.mapInArrow(lambda it: _sets(it, width), "doc_id long, cluster long, shingles binary").withColumnRenamed("doc_id", "rep"), "sets")
    load = sets.groupBy("cluster").agg(F.greatest(F.ceil(F.sum(F.length("shingles")) / (8 * block_shingles)), F.lit(1)).cast("int").alias("blocks"), F.count("*").alias("n"))
    strict = _linked(sets.join(load, "cluster"), "cluster", lambda it: _strict(it, percent))
    labels = star_components(strict.unionByName(same))
    out = cut(
        signed.select("doc_id", "n_shingles")
        .join(labels.withColumnsRenamed({"v": "doc_id", "leader": "component_id"}), "doc_id", "left")
        .select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id")),
        "near",
    )
    for done in (signed, classes, clusters, sets):
        drop_cut(done)
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def keep_one(docs: DataFrame, percent: int = 80, width: int = 5) -> DataFrame:
    """``docs`` with one document of each group of near copies: the least id.

    Rows with the same id are one document and stay or go together."""
    gone = _few(cut(near_duplicates(docs, percent, width).where("not kept").select(F.col("doc_id").alias("_gone")).distinct(), "gone"))
    return docs.join(gone, docs["doc_id"] == gone["_gone"], "left_anti")
