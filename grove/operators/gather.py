"""Gathering components: one label for each, so that a shuffle brings them together."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from grove.functions.coins import coin
from grove.operators.clique import TooManyPairs, clique_gather
from grove.operators.graph import Forest, component_labels, is_forest, require_forest
from grove.operators.ledger import RoundLedger
from grove.operators.pointers import jump_to_root
from grove.operators.rooting import root_forest
from grove.session import cut


def auto_budget(n: int, diameter: int, memory_rows: int = 50_000_000) -> int:
    """The smaller of d^3 and what the memory allows a node, at least 2."""
    return max(2, min(max(2, diameter) ** 3, memory_rows // max(1, n)))


def inspace_gather(g: Forest, diameter: int = 16, budget: int | None = None, ledger: RoundLedger | None = None) -> DataFrame:
    """(v, leader) by budgeted rooting and pointer doubling; forests only."""
    rooted = inspace_roots(g, diameter, budget, ledger)
    least = rooted.groupBy("root").agg(F.min("v").alias("leader"))
    return rooted.join(least, "root").select("v", "leader")


def inspace_roots(g: Forest, diameter: int = 16, budget: int | None = None, ledger: RoundLedger | None = None) -> DataFrame:
    """(v, root, depth) by budgeted rooting and pointer doubling."""
    b = budget or auto_budget(g.nodes.count(), diameter)
    return cut(jump_to_root(root_forest(g, b, diameter, ledger), ledger), "rooted")


def gather(g: Forest, how: str = "auto", diameter: int = 16, budget: int | None = None, ledger: RoundLedger | None = None, most_pairs: int = 20_000_000) -> DataFrame:
    """(v, leader). ``auto`` completes neighbourhoods, and gives that up before a round that would look
    at more than ``most_pairs`` pairs; then it roots in space if the graph is a forest, else labels by stars."""
    if how == "auto":
        try:
            return clique_gather(g, ledger, most_pairs=most_pairs)
        except TooManyPairs:
            how = "inspace" if is_forest(g) else "label"
    if how == "clique":
        return clique_gather(g, ledger)
    if how == "inspace":
        return inspace_gather(g, diameter, budget, ledger)
    if how == "label":
        return component_labels(g)
    raise ValueError(f"unknown way to gather: {how}")


def component_of(g: Forest, diameter: int = 16) -> DataFrame:
    """(v, leader) of a forest, checked to be one."""
    require_forest(g)
    return inspace_gather(g, diameter)


#: Components of a window that fills shelves, about.
PACKED = 50_000


def pack_components(sizes: DataFrame, capacity: int, how: str = "shelves", strict: bool = True, seed: int = 7, bins: int | None = None) -> DataFrame:
    """(leader, size, bin): whole components in bins of at most ``capacity``.

    ``shelves``: in each class of sizes within a factor 2, running sums over half the
    capacity; a window a class and a hash bucket of about ``PACKED`` components, never a
    global one. ``random``: ``bins`` bins by a coin, balanced within a log factor. A
    component over the capacity raises when ``strict``, else has its own bin."""
    row = sizes.agg(F.count("*").alias("n"), F.max("size").alias("m")).first()
    if strict and (row.m or 0) > capacity:
        raise ValueError(f"a component is larger than {capacity}")
    if how == "random":
        return sizes.select("leader", "size", F.pmod(coin("leader", seed, "bin"), F.lit(bins or 1)).alias("bin"))
    buckets = 1 + row.n // PACKED
    cls = sizes.withColumn("cls", F.when(F.col("size") > capacity, F.lit(-1)).otherwise(F.ceil(F.log2(F.col("size"))))).withColumn("part", F.pmod(F.xxhash64("leader"), F.lit(buckets)))
    rank = W.partitionBy("cls", "part").orderBy(F.desc("size"), "leader")
    before = rank.rowsBetween(W.unboundedPreceding, -1)
    shelf = F.when(F.col("size") * 2 > capacity, F.row_number().over(rank) - 1).otherwise(F.floor(F.coalesce(F.sum("size").over(before), F.lit(0)) / max(1, capacity // 2)))
    return cls.withColumn("shelf", shelf).select("leader", "size", (((F.col("cls") + 1) * buckets + F.col("part")) * 2**31 + F.col("shelf")).cast("long").alias("bin"))


def binned(labels: DataFrame, capacity: int, strict: bool = False) -> DataFrame:
    """(v, leader, bin): nodes with the packed bin of their component."""
    sizes = cut(labels.groupBy("leader").agg(F.count("*").alias("size")), "sizes")
    return labels.join(pack_components(sizes, capacity, strict=strict).select("leader", "bin"), "leader").select("v", "leader", "bin")


def colocate(df: DataFrame, labels: DataFrame, key: str = "v", capacity: int = 100_000, tasks: int | None = None) -> DataFrame:
    """Rows of ``df`` with their leader and bin, as a written table: a bin's rows lie in one file and
    a component's rows together. What reads it in groups groups by ``bin``."""
    named = df.join(binned(labels.withColumnRenamed(key, "v"), capacity).withColumnRenamed("v", key), key)
    tasks = tasks or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return cut(named.repartition(tasks, "bin").sortWithinPartitions("bin", "leader", key), "colocated")
