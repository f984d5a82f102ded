"""Degree reduction by sampling and random two-colouring.

A step samples nodes with probability D^-delta, gathers the components that the sample
induces, keeps one of each component's two colour classes by a fair coin, and deletes
it with all its neighbours. Components of the sample have no edge between them, so the
classes together are independent whatever the coins: chance only decides how fast
the degree falls.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from grove.functions.coins import coin, threshold
from grove.operators.gather import gather, inspace_roots
from grove.operators.graph import Forest, induced, max_degree, remove_closed
from grove.operators.ledger import RoundLedger
from grove.operators.local import Arrays, colours, per_task
from grove.params import TreeMisParams
from grove.session import Parts, cut, drop_cut


def sample_nodes(nodes: DataFrame, max_deg: int, delta: float, seed: int, step: int | str = 0) -> DataFrame:
    """(v): each node with probability max_deg^-delta, by its coin; no shuffle."""
    return nodes.where(coin("v", seed, f"sample{step}") < threshold(max(1, max_deg) ** -delta)).select("v")


def _md5_bits(ids: np.ndarray, seed: int, tag: str) -> np.ndarray:
    """The low bit of each id's coin, as :func:`grove.functions.coins.coin` makes it."""
    import hashlib

    return np.array([int(hashlib.md5(f"s{seed}:{tag}:{i}".encode()).hexdigest()[:13], 16) & 1 for i in ids.tolist()], np.int64)


def coin_colouring(g: Forest, labels: DataFrame, seed: int, tag: str = "colour") -> DataFrame:
    """(v, leader, black): a random one of each component's two colourings.

    Local work on co-located components: breadth-first parity plus the leader's coin."""

    def solve(t: Arrays) -> dict[str, np.ndarray]:
        root, _, depth = t.walk()
        heads, back = np.unique(t.ids[root], return_inverse=True)
        return {"v": t.ids, "leader": t.ids[root], "black": (depth + _md5_bits(heads, seed, tag)[back]) % 2 == 0}

    return per_task(g, labels, solve, "v long, leader long, black boolean")


def coin_colouring_rooted(rooted: DataFrame, seed: int, tag: str = "colour") -> DataFrame:
    """The same from (v, root, depth), as one column expression: no Python, no shuffle."""
    return rooted.select("v", F.col("root").alias("leader"), ((F.col("depth") + coin("root", seed, tag).bitwiseAND(1)) % 2 == 0).alias("black"))


def conquer_step(g: Forest, params: TreeMisParams, step: int, max_deg: int, ledger: RoundLedger | None = None) -> tuple[DataFrame, Forest, dict]:
    """(chosen(v), surviving forest, numbers) of one reduction step."""
    sampled = cut(sample_nodes(g.nodes, max_deg, params.sampling_exponent(), params.seed, step), "sampled")
    sub = induced(g, sampled).cut()
    if params.gather == "inspace":
        rooted = inspace_roots(sub, params.diameter, ledger=ledger)
        coloured = cut(coin_colouring_rooted(rooted, params.seed, f"colour{step}"), "coloured")
    else:
        labels = cut(gather(sub, params.gather, params.diameter, ledger=ledger), "labels")
        coloured = cut(coin_colouring(sub, labels, params.seed, f"colour{step}"), "coloured")
    chosen = coloured.where("black").select("v")
    if params.singleton == "join":
        chosen = chosen.unionByName(sub.nodes.join(sub.edges.select(F.col("src").alias("v")), "v", "left_anti")).distinct()
    chosen = cut(chosen, "chosen")
    rest = remove_closed(g, chosen).cut()
    largest = coloured.groupBy("leader").count().agg(F.max("count")).first()[0] or 0
    numbers = {"sampled": sampled.count(), "max_component": largest, "live": rest.nodes.count(), "delta_after": max_degree(rest)}
    drop_cut(sampled, coloured, sub.nodes, sub.edges)
    return chosen, rest, numbers


def reduce_degree(g: Forest, params: TreeMisParams, ledger: RoundLedger | None = None) -> tuple[DataFrame, Forest, list[tuple]]:
    """Steps until the degree is at the floor: (chosen, surviving forest, degree trace).

    Trace rows: (step, delta_before, delta_after, sampled, max_component, live)."""
    floor, deg = params.floor_for(g.nodes.count()), max_degree(g)
    chosen, trace, stuck, old = Parts(g.nodes.sparkSession, "reduced", "v long"), [], 0, []
    for step in range(params.max_steps):
        if deg <= floor or stuck >= params.patience:
            break
        new, g, row = conquer_step(g, params, step, deg, ledger)
        chosen.add(new)
        drop_cut(new, *old)
        old = [g.nodes, g.edges]
        trace.append((step, deg, row["delta_after"], row["sampled"], row["max_component"], row["live"]))
        stuck = stuck + 1 if row["delta_after"] >= deg else 0
        if ledger is not None:
            ledger.load(g.edges, "src")
            ledger.record("reduce_degree", rounds=1, live=row["live"], delta=row["delta_after"], note="no fall for patience steps" if stuck >= params.patience else "")
        deg = row["delta_after"]
    return chosen.frame(), g, trace


TRACE = "step int, delta_before long, delta_after long, sampled long, max_component long, live long"


def degree_trace(g: Forest, params: TreeMisParams) -> DataFrame:
    rows = reduce_degree(g, params)[2]
    return g.nodes.sparkSession.createDataFrame(rows, TRACE)


def sampled_components(g: Forest, sampled: DataFrame) -> DataFrame:
    """(leader, size): components that the sample induces."""
    return gather(induced(g, sampled), "label").groupBy("leader").agg(F.count("*").alias("size"))


def sampled_degrees(g: Forest, sampled: DataFrame, least: int) -> DataFrame:
    """(v, degree, sampled): for each node of degree ``least`` and more, how many of its neighbours the sample has."""
    near = g.edges.join(sampled.select(F.col("v").alias("dst"), F.lit(1).alias("hit")), "dst", "left")
    return near.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("degree"), F.count("hit").alias("sampled")).where(F.col("degree") >= least)


def neighbour_independence(g: Forest, sampled: DataFrame) -> DataFrame:
    """(v, sampled_neighbours, components) of each node outside the sample: equal in a forest,
    since two neighbours in one component would close a cycle."""
    labels = gather(induced(g, sampled), "label")
    near = g.edges.join(labels.withColumnsRenamed({"v": "dst"}), "dst").join(sampled.select(F.col("v").alias("src")), "src", "left_anti")
    return near.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("sampled_neighbours"), F.countDistinct("leader").alias("components"))
