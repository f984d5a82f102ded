"""What the findings of round 2 named: limits that stopped a job on larger tables."""

import random

import numpy as np
import pandas as pd
import pyarrow as pa

from grove.functions.coins import coin
from grove.llm import packing, text_arrays
from grove.operators import baselines as bl
from grove.operators import clique, rooting
from grove.operators.clique import clique_gather
from grove.operators.graph import Forest
from grove.operators.ledger import RoundLedger
from grove.operators.rooting import root_forest
from grove.plans import catalog


def test_recursion_beyond_the_row_limit(spark, sf):
    limit = "spark.sql.cteRecursionRowLimit"
    before = spark.conf.get(limit)
    spark.conf.set(limit, "50")
    try:
        got = {r.depth: r.n for r in catalog.queries()["rel_recursive_cte"](spark, sf).collect()}
        assert spark.conf.get(limit) == "50"
    finally:
        spark.conf.set(limit, before)
    assert got == {0: 1, 1: 8, 2: 64, 3: 127}


def test_one_machine_passes_what_it_cannot_hold(spark):
    r = random.Random(3)
    edges = sorted({(a, b) for a, b in ((r.randrange(80), r.randrange(80)) for _ in range(150)) if a < b})
    g = Forest.of(spark.createDataFrame(edges, "src long, dst long"), spark.range(-5, 85).withColumnRenamed("id", "v")).cut()
    ids = list(range(-5, 85))
    assert {x.v for x in bl.solo_mis(g, held_rows=10).collect()} == bl.sequential_greedy(ids, edges)
    rank = {x.v: (x.c, x.v) for x in g.nodes.select("v", coin("v", 7, "rank").alias("c")).collect()}
    assert {x.v for x in bl.prefix_greedy_mis(g, held_rows=10).collect()} == bl.sequential_greedy(ids, edges, rank)


def _sizes(sf):
    lines = pd.read_parquet(f"{sf}/lineitem.parquet")
    return {len(pd.read_parquet(f"{sf}/orders.parquet")), len(pd.read_parquet(f"{sf}/events.parquet")), len(lines.drop_duplicates(["l_orderkey", "l_linenumber"]))}


def test_plans_are_of_the_given_tables(spark, sf):
    assert {r.n for r in catalog.queries()["mpc_plan"](spark, sf).collect()} == _sizes(sf)


def test_predictions_are_of_the_given_tables(spark, sf):
    assert {r.n for r in catalog.queries()["predicted_rounds"](spark, sf).collect()} == _sizes(sf)


def test_cliques_are_not_looked_through_again(spark):
    sizes = (1, 2, 5, 40)
    stars = [(100 * k, 100 * k + i) for k, n in enumerate(sizes) for i in range(1, n + 1)]
    rest = [(1000, 1001), (1001, 1002), (1002, 1003), (1003, 1004), (2002, 2000), (2002, 2001), (2001, 2000), (2002, 2003)]
    g = Forest.of(spark.createDataFrame(stars + rest, "src long, dst long"))
    plain, short = RoundLedger(), RoundLedger()
    want = {tuple(r) for r in clique_gather(g, plain, settle_pairs=10**9).collect()}
    # completing the star of 41 nodes takes 1,640 pairs, looking through its clique 41 * 40 * 39
    assert {tuple(r) for r in clique_gather(g, short, settle_pairs=0, most_pairs=4_000).collect()} == want
    assert [r[2:] for r in short.rows] == [r[2:] for r in plain.rows]


def test_leaves_choose_before_growth(spark, monkeypatch):
    monkeypatch.setattr(rooting, "PLAIN_MASS", 0)
    # a caterpillar, a star whose greatest id is a leaf, a pair and a single node: one phase and no edge added
    edges = [(k, k + 1) for k in range(4)] + [(k, 10 * (k + 1) + i) for k in range(5) for i in range(3)] + [(200, 200 + i) for i in range(1, 6)] + [(300, 301)]
    nodes = sorted({v for e in edges for v in e} | {400})
    g, ledger = Forest.of(spark.createDataFrame(edges, "src long, dst long"), spark.createDataFrame([(v,) for v in nodes], "v long")).cut(), RoundLedger()
    up = {r.v: r.parent for r in root_forest(g, 2, ledger=ledger).collect()}
    assert sorted(up) == nodes and ledger.rows[0][9] > len(nodes) // 2 and ledger.rows[0][8] == 0
    assert {tuple(sorted(e)) for e in up.items() if e[0] != e[1]} == set(edges)
    assert sum(v == p for v, p in up.items()) == 4 and up[205] == 205 and up[300] == 301 and up[400] == 400


def test_growth_ends_once_enough_nodes_can_choose(spark, monkeypatch):
    path = Forest.of(spark.createDataFrame([(k, k + 1) for k in range(40)], "src long, dst long")).cut()
    copies = {}
    monkeypatch.setattr(rooting, "PLAIN_MASS", 0)
    for rows in (0, 10**9):
        monkeypatch.setattr(rooting, "CHECK_ROWS", rows)
        ledger = RoundLedger()
        up = {r.v: r.parent for r in root_forest(path, 10_000, ledger=ledger).collect()}
        assert len(up) == 41 and sum(v == p for v, p in up.items()) == 1 and all(abs(v - p) <= 1 for v, p in up.items())
        copies[rows] = ledger.copies()
    assert copies[0] * 4 < copies[10**9]


def test_executors_get_packed_pieces_in_small_batches(spark):
    n = 1000
    size = np.arange(n) % 4096 + 1
    ids = [np.full(k, k, "<u2").tobytes() for k in size]
    t = pa.table({"doc_id": np.arange(n), "start": np.zeros(n, np.int64), "length": size, "deal": np.arange(n), "ids": pa.array(ids, pa.binary()), "grp": np.full(n, 3)})
    got = packing._pack_group(t, 4096, "<u2")
    assert max(b.nbytes for b in got.to_batches()) <= 256 * (4 * 4096 + 64)
    assert sorted(got.column("doc_id").to_pylist()) == list(range(n))
    room = {}
    for r in got.to_pylist():
        assert r["ids"] == np.full(r["length"], r["length"], "<u4").tobytes() and r["sequence_id"] >> 24 == 3
        room.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    assert all(sum(k for _, k in x) == max(a + k for a, k in x) <= 4096 for x in room.values())
    text_arrays.whole_texts(spark.range(1))
    assert int(spark.conf.get("spark.sql.execution.arrow.maxBytesPerBatch")) <= 2 << 20


def test_pairs_are_counted_in_blocks(spark, monkeypatch):
    r = random.Random(5)
    edges = sorted({tuple(sorted(r.sample(range(60), 2))) for _ in range(70)} | {(100 + k, 101 + k) for k in range(6)} | {(200, 201 + k) for k in range(12)})
    near = {v: {b if a == v else a for a, b in edges if v in (a, b)} for e in edges for v in e}
    want = {}
    for n in near.values():
        for a in n:
            for b in n:
                if a < b and b not in near[a]:
                    want[a, b] = want.get((a, b), 0) + 1
    g = Forest.of(spark.createDataFrame(edges, "src long, dst long")).cut()
    plain, small = RoundLedger(), RoundLedger()
    labels = {tuple(x) for x in clique_gather(g, plain).collect()}
    for degree, names, rows, few in ((512, 2048, 200_000, 128), (512, 2, 10, 0), (0, 1, 1, 0), (3, 10, 10, 20)):
        for name, x in (("BLOCK_DEGREE", degree), ("BLOCK_NAMES", names), ("GROUP_ROWS", rows), ("FEW_ROWS", few)):
            monkeypatch.setattr(clique, name, x)
        assert {(x.src, x.dst): x.copies for x in clique.completion_round(g.edges, g.edges).collect()} == want
    assert {tuple(x) for x in clique_gather(g, small).collect()} == labels
    assert [x[2:] for x in small.rows] == [x[2:] for x in plain.rows]
    monkeypatch.undo()
    # 41 nodes of the same 40 neighbours: a task sends each pair on once, not 41 times
    ids = np.repeat(np.arange(41), 40)
    t = pa.table({"grp": np.zeros(1640, np.int64), "m": np.zeros(1640, np.int64), "mid": ids + 100, "dst": np.tile(np.arange(40), 41), "fresh": np.ones(1640, bool)})
    got = clique._count_pairs(t)
    assert got.num_rows == 780 and all(got.column("open").to_pylist()) and set(got.column("copies").to_pylist()) == {41}
