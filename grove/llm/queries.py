"""The opN_ queries: each applies one operator to its whole table. Their SQL is in
:mod:`grove.llm.oracles`."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from grove.llm import chat_windows, line_templates, minmax, multi_index, ngram_model, oracles, packing, private_data, quality, spaced_seeds, warc_dict
from grove.session import table


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_attention_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return quality.score(docs, quality.train(docs, table(spark, sf_dir, "labels")), threshold=0.3)


def op2_tournament_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), tokenizer_path(), end_id=2, length=4096)


def op3_budgeted_chat_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    says = "</s>[INST] ok [/INST]"
    more = spark.createDataFrame([(-1, 0, "user", says), (-1, 1, "assistant", says)], "conv_id long, turn long, role string, text string")
    return chat_windows.read_back(chat_windows.windows(rows.unionByName(more)))


def op4_weakly_supervised_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return private_data.find_personal(table(spark, sf_dir, "documents"))


def op5_dictionary_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc_dict.round_trip(table(spark, sf_dir, "pages")).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op6_inverted_multi_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings")
    return multi_index.search(vectors, vectors.where(F.col("vec_id") % 20 == 0), top=20)


def op7_spaced_seed_leaks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spaced_seeds.find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")).drop("digest")


def op8_minmax_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minmax.near_duplicates(table(spark, sf_dir, "documents"), percent=85, width=5)


def _line_report(out: DataFrame) -> DataFrame:
    return out.select("doc_id", F.col("_n_lines").alias("n_lines"), F.col("_n_dropped").alias("n_dropped"), F.md5("text").alias("text_md5"))


def op9_line_templates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _line_report(line_templates.drop_recurring(table(spark, sf_dir, "documents")))


def op9_line_templates_short(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Short lines too; the SQL of ``op9_line_templates`` leaves them."""
    return _line_report(line_templates.drop_recurring(table(spark, sf_dir, "documents"), short=True))


def op10_trie_language_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_model.score_documents(table(spark, sf_dir, "documents"))


def queries() -> dict:
    return {k: v for k, v in globals().items() if k.startswith("op") and callable(v)}


def oracle_sql() -> dict:
    return oracles.SQL
