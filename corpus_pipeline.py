"""The corpus pipeline: from raw documents to packed training sequences.

Each stage takes what its predecessor kept, written as Parquet and read again. All
stages but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from grove.llm import line_templates, minmax, packing, quality, spaced_seeds
from grove.llm.queries import tokenizer_path
from grove.session import cut, table


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Attention-based quality classifier: documents that it rejects go."""
    return quality.keep_good(docs, quality.train(docs, table(spark, sf_dir, "labels")), threshold=0.3)


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Recurring line templates are taken out of the texts; ``n_chars`` follows."""
    from pyspark.sql import functions as F

    out = line_templates.drop_recurring(docs, short=True).drop("_n_lines", "_n_dropped")
    return out.withColumn("n_chars", F.when(F.col("text").isNull(), F.col("n_chars")).otherwise(F.length("text").cast(docs.schema["n_chars"].dataType))) if "n_chars" in docs.columns else out


def keep_one_copy(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies (80 in 100, five words) stays."""
    return minmax.keep_one(docs, percent=80, width=5)


def drop_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that share a passage with the benchmark go."""
    return spaced_seeds.drop_leaks(docs, table(spark, sf_dir, "benchmark"))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """First-fit decreasing packing into sequences of 4096 tokens, ids included."""
    return packing.pack(docs, tokenizer_path(), end_id=2, length=4096, keep_ids=True)


STAGES = [
    ("quality classifier", keep_quality),
    ("line dedup", drop_lines),
    ("near dedup", keep_one_copy),
    ("benchmark decontamination", drop_benchmark),
    ("packing", pack_sequences),
]

#: A trained classifier and a tokenizer are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each but the last is written and read again."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
