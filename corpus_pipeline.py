"""Corpus pipeline over ``documents``: language, toxicity, near and substring duplicates, packing.

Each stage takes (spark, docs, sf_dir) and works on all rows that the one before it kept; all
but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from phrasework.llm import language_id, near_groups, packing, substring_dedup, toxicity
from phrasework.shared import materialize


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents whose language can't be told: no letter at all, or no language above one half.

    Null and empty texts go; null ids, repeated rows and equal texts are judged by their text alone. An
    empty table, and one without a learned language, give no rows.
    """
    return language_id.keep_identified(docs, language_id.fit_on(docs))


def clean(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents that the toxicity model scores at its threshold or above.

    Null and empty texts score lowest and stay; null ids and repeated rows are judged by their text. Without
    labels of both kinds nothing goes. An empty table gives no rows.
    """
    field = toxicity.fit_on(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return toxicity.keep_clean(docs, field)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep one document of each group of near duplicates, the one of the smallest id.

    Similarity is that of the distinct five-word shingles, 0.8 or more, and chains of it make a group; SimHash
    prints only find candidates. Of repeated rows one stays; texts without words, null ones included, are one
    group; a null id stays only where its group has no other. An empty table gives no rows.
    """
    return near_groups.keep_one_of_each(docs)


def substrings(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Remove repeated spans of 35 words and more; ``n_chars`` follows the text.

    All rows stay. Null, empty and short texts are as before; a text that is a repeated span as a whole becomes
    empty. Null ids and repeated rows count as documents of their own. An empty table gives no rows.
    """
    return substring_dedup.remove_spans(docs).withColumn("n_chars", F.length("text").cast("bigint"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pack what is left into sequences of 2048 tokens.

    Null and empty texts are the end id alone; null ids and repeated rows are packed each on its own; equal
    lengths keep the order of a hash of the row. An empty table gives no rows.
    """
    return packing.pack_documents(docs).withColumnRenamed("id", "doc_id")


STAGES = [("language_id", language), ("toxicity", clean), ("simhash_near_dedup", near_dedup), ("substring_dedup", substrings), ("packing", pack)]

#: Models and tokenizers are beyond SQL; the stages are tested against brute force instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in order, each result written to the shared folder and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
