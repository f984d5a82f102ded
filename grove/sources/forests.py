"""Forests and graphs over the given tables. Every builder returns parents(v, parent),
a root being its own parent, or plain edges(src, dst); ids are BIGINT."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from grove.operators.graph import Forest
from grove.session import cut, scratch, table

TAG = 1_000_000_000_000


def forest_of(parents: DataFrame) -> Forest:
    return Forest.of(parents.select(F.col("v").alias("src"), F.col("parent").alias("dst")), parents.select("v"))


def forest_from_fk(levels: list[tuple[DataFrame, str, int, str, int]]) -> DataFrame:
    """Parents from (child table, child key, child tag, parent key, parent tag); key expressions are SQL."""
    rows = [df.select((F.lit(ct * TAG) + F.expr(ck)).cast("long").alias("v"), (F.lit(pt * TAG) + F.expr(pk)).cast("long").alias("parent")) for df, ck, ct, pk, pt in levels]
    return reduce(DataFrame.unionByName, rows)


def commerce_tree(spark: SparkSession, d: str) -> DataFrame:
    t = lambda n: table(spark, d, n)
    lines = t("lineitem").select("l_orderkey", "l_linenumber").distinct()
    world = spark.range(1).select(F.lit(0).cast("long").alias("v"), F.lit(0).cast("long").alias("parent"))
    return world.unionByName(
        forest_from_fk(
            [
                (t("region"), "r_regionkey", 1, "0", 0),
                (t("nation"), "n_nationkey", 2, "n_regionkey", 1),
                (t("customer"), "c_custkey", 3, "c_nationkey", 2),
                (t("orders"), "o_orderkey", 4, "o_custkey", 3),
                (lines, "l_orderkey * 10 + l_linenumber", 5, "l_orderkey", 4),
            ]
        )
    )


def brand_stars(spark: SparkSession, d: str) -> DataFrame:
    hub = -F.regexp_extract("p_brand", "([0-9]+)", 1).cast("long")
    p = table(spark, d, "part")
    return p.select(F.col("p_partkey").alias("v"), hub.alias("parent")).unionByName(p.select(hub.alias("v"), hub.alias("parent")).distinct())


def forest_from_sequence(df: DataFrame, key: str, part: str | None, order: list[str]) -> DataFrame:
    """Each row's parent is the row before it in its part."""
    before = F.lag(key).over((W.partitionBy(part) if part else W.partitionBy(F.lit(0))).orderBy(*order))
    return df.select(F.col(key).cast("long").alias("v"), F.coalesce(before, F.col(key)).cast("long").alias("parent"))


def event_chains(spark: SparkSession, d: str) -> DataFrame:
    return forest_from_sequence(table(spark, d, "events"), "event_id", "user_id", ["ts", "event_id"])


def order_caterpillars(spark: SparkSession, d: str) -> DataFrame:
    spine = forest_from_sequence(table(spark, d, "orders"), "o_orderkey", "o_custkey", ["o_orderdate", "o_orderkey"])
    lines = table(spark, d, "lineitem").select("l_orderkey", "l_linenumber").distinct()
    return spine.unionByName(lines.select((F.lit(5 * TAG) + F.expr("l_orderkey * 10 + l_linenumber")).cast("long").alias("v"), F.col("l_orderkey").alias("parent")))


def _draw():
    return (F.col("k") * 1103515245 + 12345) % 2147483648


def recursive_tree(spark: SparkSession, d: str) -> DataFrame:
    k = table(spark, d, "orders").select(F.col("o_orderkey").alias("k"))
    return k.select(F.col("k").alias("v"), F.when(F.col("k") == 0, 0).otherwise(_draw() % F.col("k")).cast("long").alias("parent"))


def hub_tree(spark: SparkSession, d: str) -> DataFrame:
    k = table(spark, d, "orders").select(F.col("o_orderkey").alias("k")).withColumn("u", _draw())
    for _ in range(3):
        k = k.withColumn("p", F.shiftright((F.col("p") if "p" in k.columns else F.col("k")) * F.col("u"), 31))
    return k.select(F.col("k").alias("v"), F.col("p").cast("long").alias("parent"))


def ary_tree(spark: SparkSession, d: str, b: int, source: str = "orders") -> DataFrame:
    key = {"orders": "o_orderkey", "part": "p_partkey"}[source]
    k = table(spark, d, source).select(F.col(key).alias("k"))
    return k.select(F.col("k").alias("v"), F.when(F.col("k") == 0, 0).otherwise(F.floor((F.col("k") - 1) / b)).cast("long").alias("parent"))


def turn_paths(spark: SparkSession, d: str) -> DataFrame:
    t = table(spark, d, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), "conv_id", "turn")
    return forest_from_sequence(t, "id", "conv_id", ["turn"])


def time_line(spark: SparkSession, d: str) -> DataFrame:
    """One path over all events: a deliberate worst case. Events are ordered within their hour, and the first
    of an hour follows the last of the hour before that has any: one row an hour meets in one task."""
    e = table(spark, d, "events").select("event_id", "ts", F.date_trunc("hour", "ts").alias("hour"))
    ends = e.groupBy("hour").agg(F.max_by("event_id", F.struct("ts", "event_id")).alias("last"))
    before = ends.select("hour", F.lag("last").over(W.partitionBy(F.lit(0)).orderBy("hour")).alias("last"))
    inside = F.lag("event_id").over(W.partitionBy("hour").orderBy("ts", "event_id"))
    return e.withColumn("b", inside).join(before, "hour").select(F.col("event_id").cast("long").alias("v"), F.coalesce("b", "last", "event_id").cast("long").alias("parent"))


def trie_keys(urls: DataFrame, url: str = "url") -> DataFrame:
    """(key, parent_key): the prefixes of reversed host labels followed by path segments; the empty key is the root."""
    host = F.regexp_extract(url, "^[a-z]+://([^/?#]*)", 1)
    path = F.regexp_extract(url, "^[a-z]+://[^/?#]*([^?#]*)", 1)
    steps = F.concat(F.reverse(F.split(host, "\\.")), F.array_remove(F.split(path, "/"), ""))
    s = urls.select(steps.alias("s"))
    pre = s.select(F.explode(F.transform(F.sequence(F.lit(1), F.size("s")), lambda i: F.struct(F.array_join(F.slice("s", 1, i), "/").alias("key"), F.array_join(F.slice("s", 1, i - 1), "/").alias("parent_key")))).alias("x"))
    return pre.select("x.key", "x.parent_key").distinct()


def url_trie(spark: SparkSession, d: str) -> DataFrame:
    """Ids are the first 15 hex digits of the key's md5: the same in any engine; clashes are audited in tests."""
    num = lambda c: F.conv(F.substring(F.md5(c), 1, 15), 16, 10).cast("long")
    keys = trie_keys(table(spark, d, "pages"))
    root = spark.range(1).select(num(F.lit("")).alias("v"), num(F.lit("")).alias("parent"))
    return keys.select(num(F.col("key")).alias("v"), num(F.col("parent_key")).alias("parent")).unionByName(root)


def _directions(spark: SparkSession, d: str) -> DataFrame:
    """(id, x, n): vectors with their length; those without a direction have no neighbours."""
    dot = lambda p, q: F.aggregate(F.zip_with(p, q, lambda a, b: a * b), F.lit(0.0), lambda a, b: a + b)
    e = table(spark, d, "embeddings").select(F.col("vec_id").cast("long").alias("id"), F.col("embedding").cast("array<double>").alias("x"))
    return e.select("id", "x", F.sqrt(dot("x", "x")).alias("n")).where("n > 0 and n < double('infinity')")


def _best_of(ids: np.ndarray, x: np.ndarray, n: np.ndarray, k: int, earlier: bool, chunk: int = 2048):
    """For mapInPandas: the ``k`` best rows (a, b, cos) of each part of a batch for every query of a block.

    Products are summed in the order of the coordinates, so equal vectors tie to the last bit."""

    def run(batches):
        for batch in batches:
            batch = batch[batch["x"].map(len) == x.shape[1]].sort_values("id")
            for at in range(0, len(batch), chunk):
                part = batch.iloc[at : at + chunk]
                other, y = part["id"].to_numpy(), np.stack(part["x"].to_list())
                sim = np.zeros((len(ids), len(other)))
                for c in range(x.shape[1]):
                    sim += np.multiply.outer(x[:, c], y[:, c])
                sim /= np.multiply.outer(n, part["n"].to_numpy())
                sim[(other >= ids[:, None]) if earlier else (other == ids[:, None])] = -np.inf
                best = sim.argmax(1)[:, None] if k == 1 else np.argsort(-sim, axis=1, kind="stable")[:, :k]
                cos = np.take_along_axis(sim, best, 1)
                row, col = np.nonzero(cos > -np.inf)
                yield pd.DataFrame({"a": ids[row], "b": other[best[row, col]], "cos": cos[row, col]})

    return run


def similar_pairs(spark: SparkSession, d: str, k: int = 1, earlier: bool = True, block: int = 1024) -> DataFrame:
    """(a, b, cos): each vector's ``k`` best others (of smaller id, if ``earlier``), ties to the smaller id.

    Exact, for any number of vectors: blocks of queries come to the driver one after another and meet
    all rows where these lie; the work is the square of the rows, what is written grows with them."""
    rows = cut(_directions(spark, d), "vectors")
    found, last, empty = scratch(spark, "pairs"), None, True
    while True:
        ask = (rows if last is None else rows.where(F.col("id") > last)).orderBy("id").limit(block).toPandas()
        if ask.empty:
            break
        last = int(ask["id"].max())
        others = rows.where(F.col("id") < last) if earlier else rows
        for _, same in ask.groupby(ask["x"].map(len)):
            run = _best_of(same["id"].to_numpy(), np.stack(same["x"].to_list()), same["n"].to_numpy(), k, earlier)
            others.mapInPandas(run, "a long, b long, cos double").write.mode("append").parquet(found)
            empty = False
    if empty:
        return spark.createDataFrame([], "a long, b long, cos double")
    r = F.row_number().over(W.partitionBy("a").orderBy(F.desc("cos"), "b"))
    return spark.read.schema("a long, b long, cos double").parquet(found).withColumn("r", r).where(F.col("r") <= k).drop("r")


def nearest_earlier_tree(spark: SparkSession, d: str) -> DataFrame:
    best = similar_pairs(spark, d).select("a", "b")
    return table(spark, d, "embeddings").select(F.col("vec_id").alias("a")).join(best, "a", "left").select(F.col("a").alias("v"), F.coalesce("b", "a").alias("parent"))


def twin_documents(spark: SparkSession, d: str) -> DataFrame:
    """Edges from each document to the least id with the same text (by digest: texts are not shuffled)."""
    t = table(spark, d, "documents").where("text is not null").select("doc_id", F.md5("text").alias("h"))
    first = t.groupBy("h").agg(F.min("doc_id").alias("m"))
    return t.join(first, "h").select(F.col("doc_id").alias("src"), F.col("m").alias("dst"))


def buyer_supplier(spark: SparkSession, d: str) -> DataFrame:
    o, li = table(spark, d, "orders"), table(spark, d, "lineitem")
    return li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).select((F.lit(3 * TAG) + F.col("o_custkey")).cast("long").alias("src"), (F.lit(6 * TAG) + F.col("l_suppkey")).cast("long").alias("dst")).distinct()


def vector_neighbours(spark: SparkSession, d: str, k: int = 5) -> DataFrame:
    return similar_pairs(spark, d, k, earlier=False).select(F.col("a").alias("src"), F.col("b").alias("dst"))


FORESTS = {
    "F1": commerce_tree, "F2": brand_stars, "F3": event_chains, "F4": order_caterpillars, "F5": recursive_tree, "F6": hub_tree,
    "F7": lambda s, d: ary_tree(s, d, 8), "F8": turn_paths, "F9": url_trie, "F10": time_line, "F11": nearest_earlier_tree,
}
GRAPHS = {"G1": twin_documents, "G2": buyer_supplier, "G3": vector_neighbours}
