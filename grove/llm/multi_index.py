"""Nearest neighbours by an inverted multi-index.

Both halves of a vector are quantised by their own centroids, so k + k centroids make
k * k cells. A query ranks the centroids of each half by inner product and walks the
pairs in falling order of the sum with a heap; what lies in the cells it meets is
reranked by the exact inner product of the original vectors in double precision.

Centroids are fitted on at most ``sample`` vectors, the first by a hash of their id (a
documented bound); every vector is indexed, and the cells grow finer with the number of
vectors. A walk ends once its cells hold a share of all distinct vectors. The share is
calibrated, not guessed: among vectors that the centroids weren't fitted on (or all of
them, in a table no larger than the sample), the exact neighbours of ``PROBES`` of them
are found, and the share is what a walk must cover to meet ``recall`` of those. With
clusters it is small; neighbours of vectors without structure lie anywhere, and the
share is large. Neighbours in the whole table are nearer than those in a sample, so a
share found on a sample errs to the large side.

Equal vectors are one entry with its least ids: only those can be in a result, since
ties go to the smaller id, so a vector that a third of the rows repeat costs one
entry. Cells are put into shards of about ``SHARD`` entries (a larger cell is dealt to
several), a query visits a shard once with the cells it wants there, and a shard that
many queries visit is copied for blocks of ``VISITS`` of them: tasks stay bounded.

Defined results: vectors that are null, all zero, hold null or non-finite components
or are of another length than most take no part; rows that repeat an id and its vector
are one; a query never finds its own id; float vectors stay floats and are widened for
the products, all other numbers are doubles from the start. Scores that are equal go by
the smaller id, also where they cut the list.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from grove.session import cut

SHARD, VISITS = 8192, 4096
#: Vectors whose neighbours calibrate the share, and vectors that they are sought among.
PROBES, AMONG = 256, 20_000
#: Queries that one task walks for.
WALKS = 256


def usable(vectors: DataFrame) -> DataFrame:
    """(vec_id, embedding): the rows that take part."""
    inf = F.lit(float("inf"))
    kind = "float" if vectors.schema["embedding"].dataType.elementType.typeName() == "float" else "double"
    ok = (
        vectors.where("vec_id is not null and embedding is not null and size(embedding) > 0")
        .select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast(f"array<{kind}>").alias("embedding"))
        .where(F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != inf)) & F.exists("embedding", lambda x: x != 0))
    )
    size = ok.groupBy(F.size("embedding").alias("n")).agg(F.count("*").alias("c")).orderBy(F.desc("c"), F.desc("n")).limit(1).collect()
    return ok.where(F.size("embedding") == (size[0].n if size else 0))


def _matrix(column: pa.Array) -> np.ndarray:
    n = len(column)
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(n, -1) if n else np.zeros((0, 2), np.float32)


def _ids(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(all ids, where each row's begin and end) of a column of id lists."""
    return column.flatten().to_numpy(), np.concatenate([[0], np.cumsum(column.value_lengths().to_numpy())])


def share_for(x: np.ndarray, half: int, c1: np.ndarray, c2: np.ndarray, top: int, recall: float) -> float:
    """The share of ``x`` that walks must cover to meet ``recall`` of the exact neighbours within ``x``."""
    a, b = nearest(x[:, :half], c1), nearest(x[:, half:], c2)
    probe = np.linspace(0, len(x) - 1, min(PROBES, len(x))).astype(int)
    need = []
    for i in probe:
        exact = x @ x[i]
        exact[i] = -np.inf
        best = np.argpartition(-exact, min(top, len(x) - 1) - 1)[: min(top, len(x) - 1)]
        cell = (c1 @ x[i, :half])[a] + (c2 @ x[i, half:])[b]
        need.append(len(x) - np.searchsorted(np.sort(cell), cell[best]))
    return float(np.quantile(np.concatenate(need), recall)) / len(x)


def centroids(x: np.ndarray, k: int, rounds: int = 10, seed: int = 3) -> np.ndarray:
    """k-means by Lloyd's rounds; an empty cluster takes a random vector."""
    rng = np.random.default_rng(seed)
    c = x[rng.choice(len(x), k, replace=False)] if len(x) >= k else x[rng.integers(0, len(x), k)]
    for _ in range(rounds):
        near = nearest(x, c)
        total = np.zeros_like(c)
        np.add.at(total, near, x)
        n = np.bincount(near, minlength=k)
        empty = np.flatnonzero(n == 0)
        c = total / np.maximum(n, 1)[:, None]
        c[empty] = x[rng.integers(0, len(x), len(empty))]
    return c.astype(np.float32)


def nearest(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return np.argmin((c * c).sum(1) - 2 * (x @ c.T), 1)


def walk(first: np.ndarray, second: np.ndarray, held: list[int], want: int) -> list[int]:
    """Cells i * k + j in falling order of first[i] + second[j] until they hold ``want`` entries."""
    k = len(first)
    a, b = np.argsort(-first, kind="stable"), np.argsort(-second, kind="stable")
    fa, fb = (-first[a]).tolist(), (-second[b]).tolist()
    a, b = (a * k).tolist(), b.tolist()
    heap, reach, out, got = [(fa[0] + fb[0], 0, 0)], [-1] * (k + 1), [], 0
    push, pop = heapq.heappush, heapq.heappop
    while heap and got < want:
        _, i, j = pop(heap)
        reach[i] = j
        cell = a[i] + b[j]
        if held[cell]:
            out.append(cell)
            got += held[cell]
        if j + 1 < k and (i == 0 or reach[i - 1] > j):  # the pair before it in the other half is done
            push(heap, (fa[i] + fb[j + 1], i, j + 1))
        if i + 1 < k and reach[i + 1] == j - 1:
            push(heap, (fa[i + 1] + fb[j], i + 1, j))
    return out


def search(vectors: DataFrame, queries: DataFrame, top: int = 20, recall: float = 0.94, share: float | None = None, sample: int = 20_000, k: int | None = None) -> DataFrame:
    """(query_id, rank, vec_id, score): the ``top`` nearest found of each row of ``queries``.

    Both tables have vec_id and embedding; a candidate with the query's own id is left out.
    ``share`` overrides the calibrated share of the vectors that a walk covers."""
    good = usable(vectors)
    kind = good.schema["embedding"].dataType.simpleString()
    ranked = good.withColumn("r", F.dense_rank().over(W.partitionBy("embedding").orderBy("vec_id"))).where(F.col("r") <= top + 1)
    entries = cut(ranked.groupBy("embedding").agg(F.sort_array(F.collect_set("vec_id")).alias("ids")), "entries")
    n = entries.count()
    if n == 0:
        return vectors.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    k = k or int(min(256, max(2, round(n**0.5 / 2))))
    first_id = F.get("ids", F.lit(0))
    fit = entries.orderBy(F.xxhash64(first_id), first_id).limit(sample + AMONG).select("embedding").toArrow().column(0).combine_chunks()
    x = _matrix(fit).astype(np.float32)
    half = (x.shape[1] + 1) // 2
    c1, c2 = centroids(x[:sample, :half], k), centroids(x[:sample, half:], k)
    if share is None:
        share = share_for(x[-min(len(x), AMONG) :], half, c1, c2, top, recall) if len(x) > 1 else 1.0

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            v = _matrix(b.column("embedding")).astype(np.float32)
            cell = nearest(v[:, :half], c1) * k + nearest(v[:, half:], c2)
            yield pa.RecordBatch.from_arrays([b.column("ids"), b.column("embedding"), pa.array(cell.astype(np.int32))], names=["ids", "embedding", "cell"])

    index = cut(entries.select("ids", "embedding").mapInArrow(place, f"ids array<long>, embedding {kind}, cell int"), "index")
    held = np.zeros(k * k, np.int64)
    for r in index.groupBy("cell").agg(F.count("*").alias("n")).collect():  # at most k * k rows
        held[r.cell] = r.n
    number = held.tolist()
    copies = np.maximum(1, -(-held // SHARD))
    shard = (np.cumsum(np.minimum(held, SHARD)) - 1) // SHARD
    extra = int(shard.max()) + 1 + np.cumsum(copies - 1) - (copies - 1)
    want = max(top + 1, int(np.ceil(share * n)))

    spot = F.broadcast(vectors.sparkSession.createDataFrame([(int(c), int(shard[c]), int(extra[c]), int(copies[c])) for c in np.flatnonzero(held)], "cell int, shard long, extra long, copies long"))  # at most k * k rows
    part = F.pmod(F.xxhash64(F.get("ids", F.lit(0))), F.col("copies"))
    placed = index.join(spot, "cell").select(F.when(part == 0, F.col("shard")).otherwise(F.col("extra") + part - 1).alias("shard"), "cell", "ids", "embedding")

    def visit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            q = _matrix(b.column("embedding")).astype(np.float32)
            s1, s2 = q[:, :half] @ c1.T, q[:, half:] @ c2.T
            for i in range(len(q)):
                cells = np.array(walk(s1[i], s2[i], number, want), np.int32)
                to = [shard[cells]] + [np.array([extra[c] + m for m in range(copies[c] - 1)]) for c in cells[copies[cells] > 1]]
                what = [cells] + [np.full(copies[c] - 1, c, np.int32) for c in cells[copies[cells] > 1]]
                to, what = np.concatenate(to).astype(np.int64), np.concatenate(what)
                order = np.argsort(to, kind="stable")
                to, what = to[order], what[order]
                at = np.append(np.flatnonzero(np.diff(to, prepend=-1)), len(to))
                m = len(at) - 1
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(to[at[:-1]]), pa.array(np.full(m, b.column("query_id")[i].as_py())), b.column("embedding").take(pa.array(np.full(m, i))),
                        pa.array([what[s:e].tobytes() for s, e in zip(at[:-1], at[1:], strict=True)], pa.binary()),
                    ],
                    names=["shard", "query_id", "embedding", "cells"],
                )

    asked = usable(queries).select(F.col("vec_id").alias("query_id"), F.col("embedding").cast(kind).alias("embedding")).where(F.size("embedding") == x.shape[1]).distinct()
    asked = cut(asked, "asked")
    visits = cut(asked.repartition(1 + asked.count() // WALKS).mapInArrow(visit, f"shard long, query_id long, embedding {kind}, cells binary"), "visits")
    load = visits.groupBy("shard").agg(F.ceil(F.count("*") / VISITS).cast("int").alias("blocks"))
    left = visits.join(load, "shard").withColumn("block", F.pmod(F.xxhash64("query_id"), F.col("blocks")).cast("int")).drop("blocks")
    right = placed.join(load, "shard").withColumn("block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).drop("blocks")

    def rerank(qs: pa.Table, es: pa.Table) -> pa.Table:
        out_q, out_v, out_s = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0)]
        if qs.num_rows and es.num_rows:
            es = es.sort_by("cell")
            cell = es.column("cell").to_numpy()
            e = _matrix(es.column("embedding").combine_chunks()).astype(np.float64)
            ids, ends = _ids(es.column("ids").combine_chunks())
            names, starts = np.unique(cell, return_index=True)
            starts = np.append(starts, len(cell))
            size = np.abs(e).sum(1).max()
            q = _matrix(qs.column("embedding").combine_chunks()).astype(np.float64)
            for asker, v, cells in zip(qs.column("query_id").to_pylist(), q, qs.column("cells").to_pylist(), strict=True):
                at = np.flatnonzero(np.isin(names, np.frombuffer(cells, np.int32)))
                n = starts[at + 1] - starts[at]
                rows = np.repeat(starts[at] - np.cumsum(n) + n, n) + np.arange(n.sum())
                s = e[rows] @ v
                if len(rows) > top + 1:  # all that may be among the best, products being equal up to rounding
                    near = s >= np.partition(s, -top - 1)[-top - 1] - 1e-12 * size * np.abs(v).max()
                    rows = rows[near]
                exact = (e[rows] * v).sum(1)
                n = ends[rows + 1] - ends[rows]
                found = ids[np.repeat(ends[rows] - np.cumsum(n) + n, n) + np.arange(n.sum())]
                exact = np.repeat(exact, n)[found != asker]
                found = found[found != asker]
                best = np.lexsort((found, -exact))[:top]
                out_q.append(np.full(len(best), asker)), out_v.append(found[best]), out_s.append(exact[best])
        return pa.table({"query_id": pa.array(np.concatenate(out_q), pa.int64()), "vec_id": pa.array(np.concatenate(out_v), pa.int64()), "score": pa.array(np.concatenate(out_s), pa.float64())})

    found = left.groupBy("shard", "block").cogroup(right.groupBy("shard", "block")).applyInArrow(rerank, "query_id long, vec_id long, score double")
    order = W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score")).withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= top).select("query_id", "rank", "vec_id", "score")
