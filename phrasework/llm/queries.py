"""Queries that apply the operators of this subpackage to the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from phrasework.llm import hamming_topk, language_id, license_scan, media, packing, piece_codec, simhash, substring_dedup, toxicity, url_filter


def _table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def op1_url_filter(spark: SparkSession, folder: str) -> DataFrame:
    rules = url_filter.rules_frame(spark, url_filter.PRODUCTION_RULES)
    return url_filter.filter_urls(_table(spark, folder, "pages"), rules)


def op2_exact_topk(spark: SparkSession, folder: str) -> DataFrame:
    codes = _table(spark, folder, "embeddings").select(F.col("vec_id").alias("id"), hamming_topk.sign_code(F.col("embedding")).alias("code"))
    return hamming_topk.nearest_codes(codes, codes.where("id % 20 = 0"), k=10)


def op3_sentencepiece(spark: SparkSession, folder: str) -> DataFrame:
    return piece_codec.codec_digests(_table(spark, folder, "documents")).withColumnRenamed("id", "doc_id")


def op4_substring_dedup(spark: SparkSession, folder: str) -> DataFrame:
    return substring_dedup.removed_spans(_table(spark, folder, "documents"), width=35).withColumnRenamed("id", "doc_id")


def op5_toxicity(spark: SparkSession, folder: str) -> DataFrame:
    docs = _table(spark, folder, "documents")
    field = toxicity.fit_on(docs, _table(spark, folder, "labels"))
    return toxicity.score_texts(docs, field).select(
        F.col("id").alias("doc_id"),
        toxicity.held_out(F.col("id"), 3, 1).alias("held_out"),
        "score",
        (F.col("score") >= toxicity.THRESHOLD).cast("int").alias("predicted"),
        "toxic_words",
        F.size("spans").alias("n_spans"),
    )


def op6_language_id(spark: SparkSession, folder: str) -> DataFrame:
    docs = _table(spark, folder, "documents")
    model = language_id.fit_on(docs)
    return language_id.predict(docs, model).select(
        F.col("id").alias("doc_id"), language_id.held_out(F.col("id"), 4, 2).alias("held_out"), "lang_pred", "score"
    )


def op7_simhash_near_dedup(spark: SparkSession, folder: str) -> DataFrame:
    found = simhash.near_duplicates(_table(spark, folder, "documents"), radius=2, shingle=3, seed=42)
    return found.select(F.col("id").alias("doc_id"), F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def op8_license_scan(spark: SparkSession, folder: str) -> DataFrame:
    return license_scan.scan_licenses(_table(spark, folder, "documents"), license_scan.known_frame(spark)).withColumnRenamed("id", "doc_id")


def op9_packing(spark: SparkSession, folder: str) -> DataFrame:
    return packing.pack_documents(_table(spark, folder, "documents")).withColumnRenamed("id", "doc_id")


def op10_media_columns(spark: SparkSession, folder: str) -> DataFrame:
    return media.clip_digests(_table(spark, folder, "documents")).withColumnRenamed("id", "doc_id")


QUERIES = {f.__name__: f for f in (op1_url_filter, op2_exact_topk, op3_sentencepiece, op4_substring_dedup, op5_toxicity, op6_language_id, op7_simhash_near_dedup, op8_license_scan, op9_packing, op10_media_columns)}

ORACLES = {
    "op2_exact_topk": """
WITH codes AS (
  SELECT vec_id, list_reduce(list_prepend(0::HUGEINT, list_transform(embedding, lambda x, i: CASE WHEN x > 0 THEN 1::HUGEINT << (i - 1)::INT ELSE 0::HUGEINT END)), lambda a, b: a + b) AS code
  FROM embeddings WHERE embedding IS NOT NULL AND vec_id IS NOT NULL
), pairs AS (
  SELECT q.vec_id AS query_id, r.vec_id AS neighbor_id, CAST(bit_count(xor(q.code::UBIGINT, r.code::UBIGINT)) AS INT) AS distance
  FROM codes q, codes r WHERE q.vec_id % 20 = 0
), ranked AS (
  SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY distance, neighbor_id) AS INT) AS rank FROM pairs
)
SELECT query_id, rank, neighbor_id, distance FROM ranked WHERE rank <= 10
""",
    "op4_substring_dedup": r"""
WITH d AS (SELECT row_number() OVER () AS k, doc_id, list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
grams AS (
  SELECT k, unnest(list_transform(range(1, len(w) - 33), lambda i: md5_number(array_to_string(w[i:i + 34], ' ')))) AS h, unnest(range(1, len(w) - 33)) AS i
  FROM d WHERE len(w) >= 35
),
again AS (SELECT k, i FROM (SELECT *, count(*) OVER (PARTITION BY h) AS c FROM grams) WHERE c > 1),
words AS (SELECT k, unnest(w) AS word, unnest(range(1, len(w) + 1)) AS i FROM d),
marked AS (
  SELECT words.k, words.i, word, bool_or(again.i IS NOT NULL) OVER (PARTITION BY words.k ORDER BY words.i ROWS BETWEEN 34 PRECEDING AND CURRENT ROW) AS gone
  FROM words LEFT JOIN again ON words.k = again.k AND words.i = again.i
),
kept AS (SELECT k, count(*) FILTER (gone) AS n_removed, string_agg(word, ' ' ORDER BY i) FILTER (NOT gone) AS kept FROM marked GROUP BY 1)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_removed, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM d LEFT JOIN kept ON d.k = kept.k
""",
    "op8_license_scan": license_scan.oracle_sql(),
    "op1_url_filter": r"""
WITH cut AS (
  SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages
), parts AS (
  SELECT page_id,
         translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path
  FROM cut
), rules(action, rule_host, rule_path) AS (
  VALUES ('allow', 'com', '/'), ('block', 'example.com', '/en/'), ('allow', 'www.example.com', '/en/'), ('block', 'net', '/es/'), ('block', 'net', '/fr/')
), numbered AS (SELECT row_number() OVER () AS k, * FROM parts),
fits AS (
  SELECT k, rule_host || rule_path AS rule, action,
         row_number() OVER (PARTITION BY k ORDER BY length(rule_host || rule_path) DESC, length(rule_path)) AS place,
         count(*) OVER (PARTITION BY k) AS n
  FROM numbered JOIN rules ON (host = rule_host OR ends_with(host, '.' || rule_host)) AND starts_with(path, rule_path)
)
SELECT page_id, coalesce(host, '') AS host, coalesce(path, '') AS path, rule, coalesce(action, 'allow') AS verdict, coalesce(n, 0) AS matched_rules
FROM numbered LEFT JOIN fits ON numbered.k = fits.k AND place = 1
""",
}
