"""Connected components by alternating stars.

Public method: in turn, every node hangs its larger neighbours, then its smaller
neighbours, on the least id it can see. Each half is one aggregation and one join
on the node id, so a hub is a skewed join that Spark can split, never a group held
in memory. The edge set shrinks to one star per component around its least id.

Before the rounds the edges are dealt into blocks of bounded size and each block is
contracted by union-find to a forest of stars. That is one shuffle, and where all
edges fit one block it is the whole job.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from grove.session import cut, drop_cut


def _fingerprint(edges: DataFrame) -> tuple[int, int]:
    row = edges.agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("hi", "lo")).alias("x")).first()
    return row.n, row.x or 0


def _contract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Each node of the block with the least id of its component in the block."""
    up: dict[int, int] = {}

    def find(x: int) -> int:
        root = x
        while (y := up.setdefault(root, root)) != root:
            root = y
        while up[x] != root:
            up[x], x = root, up[x]
        return root

    for b in batches:
        for x, y in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
            x, y = find(x), find(y)
            if x != y:
                up[max(x, y)] = min(x, y)
    pairs = np.array([(v, r) for v in up if (r := find(v)) != v], np.int64).reshape(-1, 2)
    yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["hi", "lo"])


def star_components(edges: DataFrame, a: str = "src", b: str = "dst", max_rounds: int = 60, block: int = 1_000_000) -> DataFrame:
    """(v, leader) for every node that has an edge; leader is its component's least id.

    Loops, null ends and repeated edges are ignored; an empty edge table gives an
    empty result. Raises if not settled after ``max_rounds``.
    """
    x, y = F.col(a), F.col(b)
    now = cut(
        edges.where(x.isNotNull() & y.isNotNull() & (x != y))
        .select(F.greatest(x, y).cast("long").alias("hi"), F.least(x, y).cast("long").alias("lo")),
        "stars",
    )
    blocks = -(-now.count() // block)
    raw, now = now, cut(now.repartition(max(1, blocks)).mapInArrow(_contract, "hi long, lo long"), "stars")
    drop_cut(raw)
    mark = _fingerprint(now) if blocks > 1 else (0, 0)
    for _ in range(max_rounds):
        if mark[0] == 0:
            break
        both = now.select(F.col("hi").alias("at"), F.col("lo").alias("of")).unionByName(
            now.select(F.col("lo").alias("at"), F.col("hi").alias("of"))
        )
        least = both.groupBy("at").agg(F.least(F.min("of"), F.first("at")).alias("m"))
        large = both.where("of > at").join(least, "at").select(F.col("of").alias("hi"), F.col("m").alias("lo")).distinct()
        down = large.groupBy("hi").agg(F.min("lo").alias("m"))
        small = (
            large.join(down, "hi")
            .select(F.explode(F.array(F.struct(F.col("hi").alias("hi")), F.struct(F.col("lo").alias("hi")))).alias("e"), "m")
            .select(F.col("e.hi").alias("hi"), F.col("m").alias("lo"))
            .where("hi <> lo")
            .distinct()
        )
        settled = cut(small, "stars")
        drop_cut(now)
        now, before = settled, mark
        mark = _fingerprint(now)
        if mark == before:
            break
    else:
        raise RuntimeError(f"components not settled after {max_rounds} rounds")
    heads = now.select(F.col("lo").alias("v")).distinct().select("v", F.col("v").alias("leader"))
    return now.select(F.col("hi").alias("v"), F.col("lo").alias("leader")).unionByName(heads)
