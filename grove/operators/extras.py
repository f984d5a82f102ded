"""Beyond trees: matching, colourings, the line graph."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from grove.functions.coins import coin
from grove.operators.graph import Forest, degrees, without
from grove.operators.gather import inspace_roots
from grove.session import cut, drop_cut


def line_graph(g: Forest, most: int = 5_000_000, per_edge: int = 1000) -> tuple[DataFrame, Forest]:
    """(edge ids (e, src, dst), graph on them): edges are adjacent that share an end.

    It has sum of degree^2 edges; beyond ``most`` it is refused only where hubs make it more
    than ``per_edge`` times as large as the graph, however large that is."""
    size, ends = degrees(g).agg(F.sum(F.col("degree") * (F.col("degree") - 1)), F.sum("degree")).first()
    size, ends = size or 0, ends or 0
    if size > max(most, per_edge * ends // 2):
        raise ValueError(f"the line graph has {size} edges")
    named = cut(g.edges.where("src < dst").withColumn("e", F.xxhash64("src", "dst").bitwiseAND(F.lit(2**62 - 1))), "line")
    ends = named.select("e", F.col("src").alias("v")).unionByName(named.select("e", F.col("dst").alias("v")))
    pairs = ends.join(ends.withColumnRenamed("e", "f"), "v").where("e <> f").select(F.col("e").alias("src"), F.col("f").alias("dst"))
    return named, Forest.of(pairs, named.select(F.col("e").alias("v")))


def maximal_matching(g: Forest, seed: int = 7) -> DataFrame:
    """(src, dst): edges of least priority at both ends join, round by round; no line graph is made."""
    live, out, n = cut(g.edges.where("src < dst"), "match"), None, 0
    while live.count():
        p = live.withColumn("p", F.struct(coin(F.concat_ws("-", "src", "dst"), seed, f"match{n}").alias("c"), "src", "dst"))
        both = p.select(F.col("src").alias("v"), "p").unionByName(p.select(F.col("dst").alias("v"), "p"))
        best = cut(both.groupBy("v").agg(F.min("p").alias("m")), "best")
        new = cut(p.join(best.withColumnsRenamed({"v": "src", "m": "a"}), "src").join(best.withColumnsRenamed({"v": "dst", "m": "b"}), "dst").where("p = a and p = b").select("src", "dst"), "matched")
        ends = new.select(F.col("src").alias("v")).unionByName(new.select(F.col("dst").alias("v")))
        live = cut(live.join(ends.withColumnRenamed("v", "src"), "src", "left_anti").join(ends.withColumnRenamed("v", "dst"), "dst", "left_anti").select("src", "dst"), "match")
        out, n = new if out is None else out.unionByName(new), n + 1
    return out if out is not None else live


def degree_colouring(g: Forest, seed: int = 7) -> DataFrame:
    """(v, c) with at most one colour more than the maximum degree: live nodes try a random colour
    that is free within their own degree + 1, and keep it if no neighbour tries it too."""
    live, done, n = cut(degrees(g), "live"), None, 0
    while live.count():
        used = F.array().cast("array<long>")
        if done is not None:
            taken = g.edges.join(done.withColumnsRenamed({"v": "dst"}), "dst").groupBy(F.col("src").alias("v")).agg(F.collect_set("c").alias("used"))
            state = live.join(taken, "v", "left").select("v", "degree", F.coalesce("used", used).alias("used"))
        else:
            state = live.withColumn("used", used)
        free = F.array_except(F.sequence(F.lit(0).cast("long"), F.col("degree").cast("long")), F.col("used"))
        tried = cut(state.select("v", "degree", free.alias("f")).select("v", "degree", F.get("f", (coin("v", seed, f"try{n}") % F.size("f")).cast("int")).alias("c")), "tried")
        clash = g.edges.join(tried.select(F.col("v").alias("src"), F.col("c").alias("a")), "src").join(tried.select(F.col("v").alias("dst"), F.col("c").alias("b")), "dst").where("a = b and src > dst").select(F.col("src").alias("v"))
        new = cut(tried.join(clash, "v", "left_anti").select("v", "c"), "kept")
        done, n = new if done is None else cut(done.unionByName(new), "coloured"), n + 1
        live = cut(live.join(new, "v", "left_anti"), "live")
    return done if done is not None else live.select("v", F.lit(0).cast("long").alias("c"))


def edge_colouring(g: Forest, seed: int = 7) -> DataFrame:
    """(src, dst, c): the line graph coloured, under twice the maximum degree colours."""
    named, line = line_graph(g)
    return named.join(degree_colouring(line, seed).withColumnRenamed("v", "e"), "e").select("src", "dst", "c")


def two_colour(g: Forest, diameter: int = 16) -> DataFrame:
    """(v, c) with c in 0, 1: parity of the depth below the root."""
    return inspace_roots(g, diameter).select("v", (F.col("depth") % 2).cast("long").alias("c"))


def tree_max_independent_set(parents: DataFrame) -> DataFrame:
    """(root, size): the maximum set's size of each rooted tree, by levels with one aggregation each."""
    from grove.operators.pointers import jump_to_root

    rooted = cut(jump_to_root(parents).join(parents, "v"), "levels")
    top = rooted.agg(F.max("depth")).first()[0] or 0
    below = None
    for d in range(top, -1, -1):
        now = rooted.where(F.col("depth") == d).select("v", "parent", "root")
        if below is None:
            state = now.withColumns({"take": F.lit(1).cast("long"), "skip": F.lit(0).cast("long")})
        else:
            up = below.groupBy(F.col("parent").alias("v")).agg(F.sum("skip").alias("s"), F.sum(F.greatest("take", "skip")).alias("t"))
            state = now.join(up, "v", "left").select("v", "parent", "root", (F.lit(1) + F.coalesce("s", F.lit(0))).alias("take"), F.coalesce("t", F.lit(0)).cast("long").alias("skip"))
        below = cut(state, "dp")
        if d == 0:
            return below.select("root", F.greatest("take", "skip").alias("size"))
    return rooted.select("root", F.lit(0).cast("long").alias("size"))


def ancestors(parents: DataFrame, start: DataFrame) -> DataFrame:
    """``start(v, root)`` with all nodes on the way up to each root, by doubling: ceil(log2 depth) rounds."""
    up = cut(parents.where("v <> parent").select("v", F.col("parent").alias("p")), "up")
    path = cut(start.select("v", "root"), "path")
    while up.limit(1).count():
        grown = cut(path.unionByName(path.join(up, "v").select(F.col("p").alias("v"), "root")).distinct(), "path")
        farther = cut(up.join(up.select(F.col("v").alias("p"), F.col("p").alias("pp")), "p").select("v", F.col("pp").alias("p")), "up")
        drop_cut(path, up)
        path, up = grown, farther
    return path


def subtree_sizes(parents: DataFrame) -> DataFrame:
    """(v, size): nodes at and below each. A round adds to the nodes less than 2^k below a node those
    less than 2^k below the ones exactly 2^k below it: ceil(log2 depth) rounds."""
    sizes = cut(parents.select("v", F.lit(1).cast("long").alias("size")), "sizes")
    up = cut(parents.where("v <> parent").select("v", F.col("parent").alias("p")), "up")
    while up.limit(1).count():
        below = up.join(sizes, "v").groupBy(F.col("p").alias("v")).agg(F.sum("size").alias("more"))
        grown = cut(sizes.join(below, "v", "left").select("v", (F.col("size") + F.coalesce("more", F.lit(0))).alias("size")), "sizes")
        farther = cut(up.join(up.select(F.col("v").alias("p"), F.col("p").alias("pp")), "p").select("v", F.col("pp").alias("p")), "up")
        drop_cut(sizes, up)
        sizes, up = grown, farther
    return sizes


def diameters(parents: DataFrame, g: Forest) -> DataFrame:
    """(root, diameter) of each tree: the farthest node from the root, then the farthest from that one."""
    from grove.operators.pointers import jump_to_root

    rooted = cut(jump_to_root(parents), "rooted")
    far = rooted.groupBy("root").agg(F.max(F.struct("depth", "v")).alias("m")).select("root", F.col("m.v").alias("v"))
    # reroot each tree at its far node by reversing the pointers on the path to the old root
    path = ancestors(parents, far.select("v", "root"))
    on = path.select("v", F.lit(1).alias("on"))
    turned = parents.where("v <> parent").join(on, "v", "left").select(F.when(F.col("on") == 1, F.col("parent")).otherwise(F.col("v")).alias("v"), F.when(F.col("on") == 1, F.col("v")).otherwise(F.col("parent")).alias("parent"))
    again = jump_to_root(turned.unionByName(far.select("v", F.col("v").alias("parent"))))
    depth = again.groupBy(F.col("root").alias("v")).agg(F.max("depth").alias("diameter"))
    return far.join(depth, "v").select("root", "diameter")
