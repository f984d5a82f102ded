"""Canonical graphs and the set operations that every method is made of."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from grove.operators.components import star_components
from grove.session import cut


@dataclass(frozen=True)
class Forest:
    """nodes(v) and edges(src, dst), each edge in both directions, no loops, no repeats."""

    nodes: DataFrame
    edges: DataFrame

    @classmethod
    def of(cls, edges: DataFrame, nodes: DataFrame | None = None) -> Forest:
        """From rows (src, dst) in any direction; ``nodes`` adds isolated ones."""
        one = edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst")).where("src <> dst")
        both = one.unionByName(one.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).dropDuplicates()
        ends = both.select(F.col("src").alias("v"))
        if nodes is not None:
            ends = ends.unionByName(nodes.select(F.col("v").cast("long").alias("v")))
        loops = edges.where("src = dst").select(F.col("src").cast("long").alias("v"))
        return cls(ends.unionByName(loops).where("v is not null").distinct(), both)

    def cut(self) -> Forest:
        return Forest(cut(self.nodes, "nodes"), cut(self.edges, "edges"))

    def counts(self) -> tuple[int, int]:
        return self.nodes.count(), self.edges.count() // 2


def assign_ids(df: DataFrame, key: str) -> DataFrame:
    """``df`` with a BIGINT ``id`` from a 64-bit hash of ``key``; raises if two keys share one."""
    out = df.withColumn("id", F.xxhash64(key))
    twice = out.groupBy("id").agg(F.min(key).alias("a"), F.max(key).alias("b")).where("a <> b")
    if twice.limit(1).count():
        raise ValueError(f"two values of {key} have the same id")
    return out


def degrees(g: Forest) -> DataFrame:
    """(v, degree), isolated nodes with 0."""
    d = g.edges.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("degree"))
    return g.nodes.join(d, "v", "left").select("v", F.coalesce("degree", F.lit(0)).alias("degree"))


def max_degree(g: Forest) -> int:
    return g.edges.groupBy("src").count().agg(F.max("count")).first()[0] or 0


def split_by_degree(g: Forest, t: float) -> tuple[DataFrame, DataFrame]:
    """(nodes of degree below t, nodes of degree t and more)."""
    d = degrees(g)
    return d.where(F.col("degree") < t).select("v"), d.where(F.col("degree") >= t).select("v")


def induced(g: Forest, keep: DataFrame) -> Forest:
    """The subgraph on ``keep(v)``."""
    e = g.edges.join(keep.select(F.col("v").alias("src")), "src", "left_semi").join(keep.select(F.col("v").alias("dst")), "dst", "left_semi")
    return Forest(g.nodes.join(keep, "v", "left_semi"), e.select("src", "dst"))


def closed_neighbourhood(g: Forest, s: DataFrame) -> DataFrame:
    """(v): ``s`` and everything next to it."""
    near = g.edges.join(s.select(F.col("v").alias("src")), "src", "left_semi").select(F.col("dst").alias("v"))
    return s.select("v").unionByName(near).distinct()


def without(g: Forest, gone: DataFrame) -> Forest:
    """``g`` less the nodes ``gone(v)``."""
    e = g.edges.join(gone.select(F.col("v").alias("src")), "src", "left_anti").join(gone.select(F.col("v").alias("dst")), "dst", "left_anti")
    return Forest(g.nodes.join(gone, "v", "left_anti"), e.select("src", "dst"))


def remove_closed(g: Forest, s: DataFrame) -> Forest:
    return without(g, closed_neighbourhood(g, s))


def component_labels(g: Forest) -> DataFrame:
    """(v, leader) of every node; leader is the component's least id."""
    labels = star_components(g.edges)
    return g.nodes.join(labels, "v", "left").select("v", F.coalesce("leader", "v").alias("leader"))


def is_forest(g: Forest) -> bool:
    """Acyclic: as many edges as nodes less components."""
    n, m = g.counts()
    return m == n - component_labels(g).select("leader").distinct().count()


def require_forest(g: Forest) -> None:
    if not is_forest(g):
        raise ValueError("the graph has a cycle; this method needs a forest")


def two_hop(g: Forest) -> DataFrame:
    """(src, dst): pairs at distance exactly 2."""
    a, b = g.edges.select(F.col("src").alias("mid"), F.col("dst").alias("src")), g.edges.select(F.col("src").alias("mid"), "dst")
    return a.join(b, "mid").where("src <> dst").select("src", "dst").distinct().join(g.edges, ["src", "dst"], "left_anti")
