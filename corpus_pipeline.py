"""Corpus pipeline: quality, near duplicates, benchmark leaks, personal data, token ids.

Each stage takes the documents that its predecessor kept, reread from Parquet, and decides for all of them; the last one
adds the ids. A stage judges by its own input: classes of near duplicates, for instance, are those of the documents left.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockquant.llm import bm25_leaks, bpe_prefix, common, compression_quality, order_minhash, pii_feistel

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents the compression classifier doesn't reject."""
    model = compression_quality.fit_on_labels(docs, common.table(spark, sf_dir, "labels"))
    return compression_quality.score(docs.select(*COLUMNS), model, out="__score").where(F.col("__score") >= 0.5).select(*COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class, that of the smallest id."""
    classes = order_minhash.near_duplicates(docs)
    gone = classes.where(F.col("doc_id") != F.col("class_id")).select("doc_id").distinct()
    return docs.select(*COLUMNS).join(gone, "doc_id", "left_anti").select(*COLUMNS)


def benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that leak no benchmark item. The few that leak are told apart by a second, equal reading, not by a copy of all texts."""
    leaks = bm25_leaks.find_leaks(docs, common.table(spark, sf_dir, "benchmark")).select("doc_id").distinct()
    return docs.select(*COLUMNS).join(leaks, "doc_id", "left_anti").select(*COLUMNS)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document, with pseudonyms in its text and the new text's length."""
    out = pii_feistel.pseudonymise(docs.select(*COLUMNS), pii_feistel.DEMO_KEY, count="__n_pii")
    return out.select("doc_id", "text", "lang", "source", F.when(F.col("__n_pii") > 0, F.length("text")).otherwise(F.col("n_chars")).cast("long").alias("n_chars"))


def token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document with its ids (little-endian uint32) and their number."""
    import public_tokenizers

    out = bpe_prefix.encode(docs.select(*COLUMNS), public_tokenizers.path("word_bpe_49k.json"))
    return out.withColumn("n_tokens", bpe_prefix.n_ids("ids"))


STAGES = [
    ("quality", quality),
    ("near_duplicates", near_duplicates),
    ("benchmark_leaks", benchmark_leaks),
    ("personal_data", personal_data),
    ("token_ids", token_ids),
]

#: No stage but the fourth's columns can be had from SQL: tests/llm compares each with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = common.stored(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
