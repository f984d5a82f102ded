"""Completion of whole components in large jobs: the same rounds, with a component's edges as a matrix.

Where a component is dealt changes the work, never a result: nodes are dealt by the least id of their component, and every
round still joins all pairs of neighbours. A small component runs its rounds in its task. One of more than
``SMALL`` nodes lies in strips of matrix rows, a bit a pair; a round multiplies the strips two by two,
so its k^2 edges are k^2 / 8 bytes and not rows."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from grove.session import cut, drop_cut

#: Nodes up to which a component is a task's; nodes up to which it is completed in strips; matrix rows of a strip; rows of a task's group, about.
SMALL, LARGEST, STRIP, GROUP_ROWS = 1_024, 40_000, 1_024, 100_000

_ROUND = "leader long, strip int, other int, k int, bits binary, full boolean, copies long, edges long"


def homes(edges: DataFrame) -> DataFrame:
    """(v, leader) of every node of edges(src, dst), both ways: the least id of its component. Nodes hang on the
    least neighbour and pointers double up to a node that has no lesser one; what is joined beyond that is
    contracted and goes on likewise. Where ids rise along the components that is one pass."""
    now, labels = edges.select("src", "dst"), None
    while True:
        up = cut(now.groupBy(F.col("src").alias("v")).agg(F.least(F.min("dst"), F.first("src")).alias("m")), "homes")
        moved = 1
        while moved:
            far = cut(up.join(up.select(F.col("v").alias("m"), F.col("m").alias("to")), "m").select("v", F.col("to").alias("m"), (F.col("to") != F.col("m")).alias("moved")), "homes")
            moved = far.where("moved").limit(1).count()
            drop_cut(up)
            up = far.select("v", "m")
        if labels is None:
            labels = up.withColumnRenamed("m", "leader")
        else:
            labels = cut(labels.join(up.withColumnRenamed("v", "leader"), "leader", "left").select("v", F.coalesce("m", "leader").alias("leader")), "labels")
        across = now.join(up.withColumnsRenamed({"v": "src", "m": "a"}), "src").join(up.withColumnsRenamed({"v": "dst", "m": "b"}), "dst").where("a <> b")
        now = cut(across.select(F.col("a").alias("src"), F.col("b").alias("dst")).distinct(), "across")
        if not now.limit(1).count():
            return labels


def deal(edges: DataFrame) -> DataFrame:
    """(v, leader, k): nodes that have an edge, with their component's label and size."""
    labels = homes(edges)
    return cut(labels.join(labels.groupBy("leader").agg(F.count("*").alias("k")), "leader").select("v", "leader", "k"), "dealt")


def segments(t: pa.Table, key: str) -> list[tuple[int, int]]:
    """The ranges of equal ``key`` in a sorted table."""
    x = t.column(key).to_numpy()
    starts = np.flatnonzero(np.diff(x, prepend=x[0] - 1))
    return list(zip(starts.tolist(), [*starts[1:].tolist(), len(x)], strict=True))


def _complete(t: pa.Table) -> pa.Table:
    """(v, leader) of each node of the group's components, and (n, copies, edges) of their rounds."""
    t = t.sort_by("leader")
    src, dst = (t.column(c).to_numpy() for c in ("src", "dst"))
    names, labels, totals = [], [], {}
    for start, end in segments(t, "leader"):
        ids, a = np.unique(src[start:end], return_inverse=True)
        near = np.zeros((len(ids), len(ids)), np.float32)
        near[a, np.searchsorted(ids, dst[start:end])] = 1
        for n in range(64):
            count = near @ near
            new = (count > 0) & (near == 0)
            np.fill_diagonal(new, False)
            if not new.any():
                break
            c, e = totals.get(n, (0, 0))
            totals[n] = (c + int(count[new].sum(dtype=np.float64)) // 2, e + np.count_nonzero(new) // 2)
            near[new] = 1
        np.fill_diagonal(near, 1)
        names.append(ids)
        labels.append(ids[near.argmax(1)])
    v, m = np.concatenate(names), np.concatenate(labels)
    none, rounds = [None] * len(totals), sorted(totals)
    return pa.table(
        {
            "v": pa.array([*v.tolist(), *none], pa.int64()), "leader": pa.array([*m.tolist(), *none], pa.int64()),
            "n": pa.array([None] * len(v) + rounds, pa.int32()),
            "copies": pa.array([None] * len(v) + [totals[n][0] for n in rounds], pa.int64()), "edges": pa.array([None] * len(v) + [totals[n][1] for n in rounds], pa.int64()),
        }
    )


def complete_small(named: DataFrame) -> tuple[list[tuple[int, int]], DataFrame]:
    """([(copies, edges)] of each round, (v, leader)) of the components in named(leader, src, dst)."""
    groups = 1 + named.count() // GROUP_ROWS
    out = cut(named.groupBy(F.pmod(F.xxhash64("leader"), F.lit(groups))).applyInArrow(_complete, "v long, leader long, n int, copies long, edges long"), "completed")
    rows = out.where("n is not null").groupBy("n").agg(F.sum("copies").alias("c"), F.sum("edges").alias("e")).orderBy("n").collect()
    return [(r.c, r.e) for r in rows], out.where("v is not null").select("v", "leader")


def _unpack(bits: bytes, k: int) -> np.ndarray:
    return np.unpackbits(np.frombuffer(bits, np.uint8).reshape(-1, (k + 7) // 8), axis=1, count=k)


def _rows_out(rows: list[tuple]) -> pa.Table:
    types = (("leader", pa.int64()), ("strip", pa.int32()), ("other", pa.int32()), ("k", pa.int32()), ("bits", pa.binary()), ("full", pa.bool_()), ("copies", pa.int64()), ("edges", pa.int64()))
    return pa.table({name: pa.array([r[i] for r in rows], kind) for i, (name, kind) in enumerate(types)})


def _strip(leader: int, strip: int, near: np.ndarray) -> tuple:
    """A strip's row; it is full if each of its nodes has all others for neighbours."""
    k = near.shape[1]
    return leader, strip, -1, k, np.packbits(near, axis=1).tobytes(), int(near.sum(dtype=np.int64)) == len(near) * (k - 1), 0, 0


def _first(t: pa.Table, size: int) -> pa.Table:
    leader, k, strip = (t.column(c)[0].as_py() for c in ("leader", "k", "strip"))
    near = np.zeros((min(size, k - strip * size), k), np.uint8)
    near[t.column("i").to_numpy() - strip * size, t.column("j").to_numpy()] = 1
    return _rows_out([_strip(leader, strip, near)])


def _tile(t: pa.Table, size: int) -> pa.Table:
    """The pairs between two strips that a round adds, for each of the two, and how often they are added."""
    by = {r["strip"]: r for r in t.select(["leader", "strip", "k", "bits"]).to_pylist()}
    a, b = min(by), max(by)
    leader, k = by[a]["leader"], by[a]["k"]
    x = _unpack(by[a]["bits"], k)
    y = x if a == b else _unpack(by[b]["bits"], k)
    open_ = x[:, b * size : b * size + len(y)] == 0
    if a == b:
        np.fill_diagonal(open_, False)
    row, col = np.flatnonzero(open_.any(1)), np.flatnonzero(open_.any(0))
    at, mid = np.ix_(row, col), np.flatnonzero(x.any(0) & y.any(0))  # only nodes near both strips add a pair
    count = x[np.ix_(row, mid)].astype(np.float32) @ y[np.ix_(col, mid)].astype(np.float32).T
    new = (count > 0) & open_[at]
    if not new.any():
        return _rows_out([])
    half = 2 if a == b else 1
    block = np.zeros(open_.shape, np.uint8)
    block[at] = new
    sums = int(count[new].sum(dtype=np.float64)) // half, np.count_nonzero(new) // half
    rows = [(leader, a, b, k, np.packbits(block, axis=1).tobytes(), False, *sums)]
    return _rows_out(rows if a == b else [*rows, (leader, b, a, k, np.packbits(block.T, axis=1).tobytes(), False, 0, 0)])


def _merge(t: pa.Table, size: int) -> pa.Table:
    """A strip with what a round adds to it."""
    rows = t.to_pylist()
    old = next(r for r in rows if r["other"] < 0)
    near = _unpack(old["bits"], old["k"])
    for r in rows:
        if r["other"] >= 0:
            at = r["other"] * size
            wide = min(size, old["k"] - at)
            near[:, at : at + wide] |= _unpack(r["bits"], wide)
    return _rows_out([_strip(old["leader"], old["strip"], near)])


def _least(t: pa.Table, size: int) -> pa.Table:
    r = t.to_pylist()[0]
    near = _unpack(r["bits"], r["k"])
    i = np.arange(len(near)) + r["strip"] * size
    near[np.arange(len(near)), i] = 1
    return pa.table({"leader": pa.array([r["leader"]] * len(i), pa.int64()), "i": pa.array(i, pa.int64()), "j": pa.array(near.argmax(1), pa.int64())})


def complete_strips(named: DataFrame, dealt: DataFrame) -> tuple[list[tuple[int, int]], DataFrame]:
    """([(copies, edges)] of each round, (v, leader)) of the components in named(leader, k, src, dst), whose nodes are dealt(v, leader)."""
    place = cut(dealt.select("leader", "v", (F.row_number().over(W.partitionBy("leader").orderBy("v")) - 1).cast("long").alias("i")), "places")
    size = STRIP  # as it is here: tasks import this module anew
    ends = named.join(place.select(F.col("v").alias("src"), "i"), "src").join(place.select(F.col("v").alias("dst"), F.col("i").alias("j")), "dst")
    strips = cut(ends.withColumn("strip", F.floor(F.col("i") / size).cast("int")).groupBy("leader", "strip").applyInArrow(lambda t: _first(t, size), _ROUND), "strips")
    totals = []
    while True:
        # a full strip has no pair to add; two others meet once
        todo = strips.where("not full")
        each = todo.join(todo.select("leader", F.col("strip").alias("with")), "leader")
        meet = each.select("leader", F.least("strip", "with").alias("a"), F.greatest("strip", "with").alias("b"), "strip", "k", "bits")
        new = cut(meet.groupBy("leader", "a", "b").applyInArrow(lambda t: _tile(t, size), _ROUND), "tiles")
        row = new.agg(F.sum("copies").alias("c"), F.sum("edges").alias("e")).first()
        if not row.e:
            drop_cut(new)
            break
        totals.append((row.c, row.e))
        grown = cut(strips.unionByName(new).groupBy("leader", "strip").applyInArrow(lambda t: _merge(t, size), _ROUND), "strips")
        drop_cut(strips, new)
        strips = grown
    least = strips.groupBy("leader", "strip").applyInArrow(lambda t: _least(t, size), "leader long, i long, j long")
    labels = cut(least.join(place, ["leader", "i"]).select("v", "leader", F.col("j").alias("i")).join(place.select("leader", "i", F.col("v").alias("m")), ["leader", "i"]).select("v", F.col("m").alias("leader")), "labels")
    drop_cut(strips, place)
    return totals, labels


def complete_whole(edges: DataFrame) -> tuple[list[tuple[int, int]], DataFrame, DataFrame]:
    """([(copies, edges)] of each round, (v, leader), the edges of the components that are too large) for edges(src, dst, ..)."""
    dealt = deal(edges)
    named = cut(edges.join(dealt.withColumnRenamed("v", "src"), "src"), "named")
    n = dealt.agg(F.max("k").alias("most")).first().most or 0
    totals, labels = complete_small(named.where(F.col("k") <= SMALL).select("leader", "src", "dst"))
    if n > SMALL:
        middle = F.col("k").between(SMALL + 1, LARGEST)
        more, others = complete_strips(named.where(middle).select("leader", F.col("k").cast("int").alias("k"), "src", "dst"), dealt.where(middle))
        both = [(totals[i] if i < len(totals) else (0, 0), more[i] if i < len(more) else (0, 0)) for i in range(max(len(totals), len(more)))]
        totals, labels = [(a[0] + b[0], a[1] + b[1]) for a, b in both], labels.unionByName(others)
    rest = cut(named.where(F.col("k") > LARGEST).select(edges.columns), "clique")
    drop_cut(named, dealt)
    return totals, labels, rest
