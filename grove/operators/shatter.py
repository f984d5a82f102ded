"""Low-degree shattering by desire levels.

A live node has desire 2^-e. A round marks it with that probability; a marked node
without a marked neighbour joins the set and leaves with its neighbours; then its
desire halves if its neighbours' desires sum to 2 or more, and doubles up to a half
otherwise. Levels are integers, so the sums are exact in any order.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from grove.functions.coins import SIDES, coin
from grove.operators.graph import Forest, remove_closed
from grove.operators.ledger import RoundLedger
from grove.session import Parts, cut, drop_cut

CAP = 50


def desire_round(g: Forest, state: DataFrame, seed: int, n: int) -> DataFrame:
    """(v, e, joins): next levels, and who joins, from state(v, e). One exchange on the edges."""
    said = state.select("v", "e", (coin("v", seed, f"mark{n}") < F.lit(SIDES) / F.pow(F.lit(2.0), F.col("e"))).alias("marked"), F.pow(F.lit(2.0), -F.col("e")).alias("want"))
    near = (
        g.edges.join(said.select(F.col("v").alias("dst"), "marked", "want"), "dst")
        .groupBy(F.col("src").alias("v")).agg(F.max("marked").alias("any"), F.sum("want").alias("sum"))
    )
    return said.join(near, "v", "left").select(
        "v", F.when(F.coalesce("sum", F.lit(0.0)) >= 2, F.least(F.col("e") + 1, F.lit(CAP))).otherwise(F.greatest(F.col("e") - 1, F.lit(1))).alias("e"), (F.col("marked") & ~F.coalesce("any", F.lit(False))).alias("joins")
    )


def shatter(g: Forest, rounds: int, seed: int = 7, ledger: RoundLedger | None = None, stop_empty: bool = True) -> tuple[DataFrame, Forest]:
    """(chosen(v), what is left) after ``rounds`` rounds."""
    chosen, state, old = Parts(g.nodes.sparkSession, "shattered", "v long"), g.nodes.select("v", F.lit(1).alias("e")), []
    for n in range(rounds):
        nxt = cut(desire_round(g, state, seed, n), "desire")
        g = remove_closed(g, chosen.add(nxt.where("joins").select("v"))).cut()
        drop_cut(*old)
        old, state = [nxt, g.nodes, g.edges], nxt.select("v", "e").join(g.nodes, "v", "left_semi")
        live = g.nodes.count()
        if ledger is not None:
            ledger.load(g.edges, "src")
            ledger.record("shatter", rounds=1, live=live)
        if stop_empty and live == 0:
            break
    return chosen.frame(), g


def leftover_sizes(g: Forest) -> DataFrame:
    """(size, components): how large what is left is."""
    from grove.operators.graph import component_labels

    return component_labels(g).groupBy("leader").count().groupBy(F.col("count").alias("size")).agg(F.count("*").alias("components"))
