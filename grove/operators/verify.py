"""Certificates: what must hold whatever the coins were."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from grove.operators.graph import Forest, closed_neighbourhood


def certify_mis(g: Forest, s: DataFrame) -> DataFrame:
    """One row (n_nodes, n_edges, inside_edges, undominated): the last two are 0 for a maximal independent set."""
    inside = g.edges.join(s.select(F.col("v").alias("src")), "src", "left_semi").join(s.select(F.col("v").alias("dst")), "dst", "left_semi").agg((F.count("*") / 2).cast("long").alias("inside_edges"))
    alone = g.nodes.join(closed_neighbourhood(g, s), "v", "left_anti").agg(F.count("*").alias("undominated"))
    n, m = g.nodes.agg(F.count("*").alias("n_nodes")), g.edges.agg((F.count("*") / 2).cast("long").alias("n_edges"))
    return n.crossJoin(m).crossJoin(inside).crossJoin(alone)  # four one-row tables


def certify_matching(edges: DataFrame, matching: DataFrame) -> DataFrame:
    """One row (shared_ends, addable): both 0 for a maximal matching(src, dst)."""
    ends = matching.select(F.col("src").alias("v")).unionByName(matching.select(F.col("dst").alias("v")))
    shared = ends.groupBy("v").count().where("count > 1").agg(F.count("*").alias("shared_ends"))
    e = ends.distinct()
    free = edges.join(e.select(F.col("v").alias("src")), "src", "left_anti").join(e.select(F.col("v").alias("dst")), "dst", "left_anti").agg(F.count("*").alias("addable"))
    return shared.crossJoin(free)


def certify_colouring(g: Forest, colour: DataFrame) -> DataFrame:
    """One row (uncoloured, clashes, colours_over): colour(v, c) against edges and the degree bound."""
    a, b = colour.withColumnsRenamed({"v": "src", "c": "cs"}), colour.withColumnsRenamed({"v": "dst", "c": "cd"})
    clash = g.edges.join(a, "src").join(b, "dst").where("cs = cd").agg(F.count("*").alias("clashes"))
    deg = g.edges.groupBy(F.col("src").alias("v")).count().agg(F.coalesce(F.max("count"), F.lit(0)).alias("d"))
    over = colour.agg(F.coalesce(F.max("c"), F.lit(0)).alias("m")).crossJoin(deg).select((F.col("m") > F.col("d")).cast("long").alias("colours_over"))
    return g.nodes.join(colour, "v", "left_anti").agg(F.count("*").alias("uncoloured")).crossJoin(clash).crossJoin(over)
