"""Pointer doubling over rooted forests.

State (v, p, k): p is v's ancestor k steps up. A round replaces p by p's own p and
adds the steps; a root points to itself with 0 steps, so arrived rows keep theirs.
ceil(log2 depth) rounds change something, and the run ends when every p is a root.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from grove.operators.ledger import RoundLedger
from grove.session import cut, drop_cut


def jump_to_root(parents: DataFrame, ledger: RoundLedger | None = None, max_rounds: int = 64) -> DataFrame:
    """(v, root, depth) from parents(v, parent), where a root is its own parent.

    Raises on a cycle, which never settles."""
    start = parents.select("v", F.col("parent").alias("p"), (F.col("v") != F.col("parent")).cast("long").alias("k"))
    roots = start.where("k = 0").select(F.col("v").alias("root"))
    now = cut(start, "jump")
    for n in range(max_rounds):
        # a pointer has arrived once its target is a root: k then stays
        nxt = now.alias("a").join(now.select(F.col("v").alias("p"), F.col("p").alias("pp"), F.col("k").alias("kk")), "p").select("v", F.col("pp").alias("p"), (F.col("k") + F.col("kk")).alias("k"))
        moved = cut(nxt, "jump")
        live = moved.join(roots.select(F.col("root").alias("p")), "p", "left_anti").count()
        drop_cut(now)
        now = moved
        if ledger is not None:
            ledger.load(now, "v")
            ledger.traffic(now, "v", "p")
            ledger.record("jump_to_root", rounds=1, live=live)
        if live == 0:
            return now.select("v", F.col("p").alias("root"), F.col("k").alias("depth"))
    raise ValueError("pointers do not reach a root: the parents have a cycle")
