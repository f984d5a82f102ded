"""Edge lists, adjacency lists and parent tables in and out."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

EDGE = T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType())])


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", src: str = "src", dst: str = "dst", sep: str = ",") -> DataFrame:
    """(src, dst) from parquet, orc, json, csv, tsv or text ("a b" a line); malformed rows give null ends and go."""
    if fmt == "text":
        parts = F.split(F.trim("value"), "\\s+")
        out = spark.read.text(path).select(F.try_element_at(parts, F.lit(1)).try_cast("long").alias("src"), F.try_element_at(parts, F.lit(2)).try_cast("long").alias("dst"))
    elif fmt in ("csv", "tsv"):
        out = spark.read.schema(T.StructType([T.StructField(src, T.LongType()), T.StructField(dst, T.LongType())])).csv(path, sep="\t" if fmt == "tsv" else sep, header=True, enforceSchema=False)
    elif fmt == "json":
        out = spark.read.schema(T.StructType([T.StructField(src, T.LongType()), T.StructField(dst, T.LongType())])).json(path)
    else:
        out = spark.read.format(fmt).load(path)
    if fmt != "text":
        out = out.select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst"))
    return out.where("src is not null and dst is not null")


def write_edges(edges: DataFrame, path: str, fmt: str = "parquet", mode: str = "errorifexists") -> None:
    e = edges.select("src", "dst")
    if fmt == "text":
        e.select(F.concat_ws(" ", "src", "dst").alias("value")).write.mode(mode).text(path)
    elif fmt in ("csv", "tsv"):
        e.write.mode(mode).csv(path, sep="\t" if fmt == "tsv" else ",", header=True)
    else:
        e.write.mode(mode).format(fmt).save(path)


def to_adjacency(edges: DataFrame, most: int = 100_000) -> DataFrame:
    """(v, neighbours), for looking at; nodes of more than ``most`` neighbours raise rather than fill a task."""
    deg = edges.groupBy("src").count().agg(F.max("count")).first()[0] or 0
    if deg > most:
        raise ValueError(f"a node has {deg} neighbours")
    return edges.groupBy(F.col("src").alias("v")).agg(F.sort_array(F.collect_set("dst")).alias("neighbours"))


def explode_adjacency(adjacency: DataFrame) -> DataFrame:
    return adjacency.select(F.col("v").alias("src"), F.explode("neighbours").alias("dst"))


def write_labels(labels: DataFrame, path: str, mode: str = "errorifexists", buckets: int = 16) -> None:
    """Parquet by a bucket of the leader, so that a component's rows are pruned to one folder."""
    labels.withColumn("bucket", F.pmod(F.xxhash64("leader"), F.lit(buckets))).repartition("bucket").write.mode(mode).partitionBy("bucket").parquet(path)


def save_bucketed(edges: DataFrame, name: str, buckets: int = 16) -> None:
    """Adjacency as a table bucketed and sorted by src: later joins on src need no shuffle."""
    edges.select("src", "dst").write.mode("overwrite").bucketBy(buckets, "src").sortBy("src").saveAsTable(name)


def register_views(edges: DataFrame, labels: DataFrame | None = None) -> None:
    edges.createOrReplaceTempView("grove_edges")
    if labels is not None:
        labels.createOrReplaceTempView("grove_labels")
