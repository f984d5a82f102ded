"""Component labelling baselines; every one returns (v, leader), leader the least id."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from grove.functions.coins import SIDES, coin
from grove.operators.graph import Forest
from grove.operators.ledger import RoundLedger
from grove.session import cut, drop_cut


def flood_labels(g: Forest, ledger: RoundLedger | None = None, max_rounds: int = 10_000) -> DataFrame:
    """The least id spreads one hop a round: as many rounds as the diameter."""
    now = cut(g.nodes.select("v", F.col("v").alias("leader")), "flood")
    for _ in range(max_rounds):
        near = g.edges.join(now.select(F.col("v").alias("dst"), F.col("leader").alias("m")), "dst").groupBy(F.col("src").alias("v")).agg(F.min("m").alias("m"))
        nxt = cut(now.join(near, "v", "left").select("v", F.least("leader", F.coalesce("m", "leader")).alias("leader"), (F.col("m") < F.col("leader")).alias("moved")), "flood")
        moved = nxt.where("moved").count()
        drop_cut(now)
        now = nxt.select("v", "leader")
        if ledger is not None:
            ledger.record("flood_labels", rounds=1, live=moved)
        if moved == 0:
            return now
    raise RuntimeError("not settled")


def minset_labels(g: Forest, ledger: RoundLedger | None = None, max_rounds: int = 64) -> DataFrame:
    """Every node sends the set it holds to the set's least member, and that member to the set."""
    now = cut(g.edges.select(F.col("src").alias("holder"), F.col("dst").alias("member")).unionByName(g.nodes.select(F.col("v").alias("holder"), F.col("v").alias("member"))), "minset")
    for _ in range(max_rounds):
        least = now.groupBy("holder").agg(F.min("member").alias("m"))
        held = now.join(least, "holder")
        nxt = cut(held.select(F.col("m").alias("holder"), "member").unionByName(held.select(F.col("member").alias("holder"), F.col("m").alias("member"))).distinct(), "minset")
        moved = nxt.join(now, ["holder", "member"], "left_anti").count() + now.join(nxt, ["holder", "member"], "left_anti").count()
        drop_cut(now)
        now = nxt
        if ledger is not None:
            ledger.record("minset_labels", rounds=1, live=moved)
        if moved == 0:
            return now.groupBy(F.col("holder").alias("v")).agg(F.min("member").alias("leader"))
    raise RuntimeError("not settled")


def contract_labels(g: Forest, seed: int = 7, ledger: RoundLedger | None = None, max_rounds: int = 200) -> DataFrame:
    """Tails join the least head next to them, and the graph of groups goes on."""
    label = cut(g.nodes.select("v", F.col("v").alias("c")), "contract")
    edges = cut(g.edges.select("src", "dst"), "contract")
    for n in range(max_rounds):
        live = edges.count()
        if ledger is not None:
            ledger.record("contract_labels", rounds=1, live=live)
        if live == 0:
            least = label.groupBy("c").agg(F.min("v").alias("leader"))
            return label.join(least, "c").select("v", "leader")
        head = lambda c: coin(c, seed, f"contract{n}") < SIDES // 2
        to = cut(edges.where(~head("src") & head("dst")).groupBy(F.col("src").alias("c")).agg(F.min("dst").alias("to")), "join")
        old = (label, edges, to)
        label = cut(label.join(to, "c", "left").select("v", F.coalesce("to", "c").alias("c")), "contract")
        moved = edges.join(to.withColumnsRenamed({"c": "src", "to": "a"}), "src", "left").join(to.withColumnsRenamed({"c": "dst", "to": "b"}), "dst", "left")
        edges = cut(moved.select(F.coalesce("a", "src").alias("src"), F.coalesce("b", "dst").alias("dst")).where("src <> dst").distinct(), "contract")
        drop_cut(*old)
    raise RuntimeError("not settled")
