"""Queries of the training-data operators over the tables of a folder, and DuckDB SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wsig.llm.quality_rules import quality_rules

    out = quality_rules(_table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "lang", "log_ppl", "low", "high")


def op2_weak_label(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wsig.llm.weak_label import weak_label_quality

    out = weak_label_quality(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))
    return out.select("doc_id", "kept", "score", "posterior", F.col("flagged").alias("toxic"), F.col("label_score").alias("toxic_score"))


def op3_simhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wsig.llm.simhash import simhash_groups

    out = simhash_groups(_table(spark, sf_dir, "documents"))
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op5_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wsig.llm.mixing import curriculum

    out = curriculum(_table(spark, sf_dir, "documents"))
    return out.select("doc_id", "size", "source_size", "target", "taken", "source", "copies", "position", "last_position")


def op8_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wsig.llm.url_filter import LISTED, url_filter

    listed = spark.createDataFrame([(x,) for x in LISTED], "key string")
    return url_filter(_table(spark, sf_dir, "pages"), listed).select("page_id", "host", "path", "rule", "verdict")


def _op8_sql() -> str:
    from wsig.llm.url_filter import LISTED

    listed = ", ".join(f"('{x}')" for x in LISTED)
    return f"""
WITH cut AS (
  SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
parts AS (SELECT page_id, rest, regexp_extract(rest, '^[^/?#]*', 0) AS h FROM cut),
p AS (
  SELECT page_id, translate(h, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         regexp_extract(substr(rest, length(h) + 1), '^[^?#]*', 0) AS path FROM parts),
rules(h, q, v) AS (VALUES ('com', '/', 'allow'), ('example.com', '/en/', 'block'), ('www.example.com', '/en/', 'allow'),
                          ('net', '/es/', 'block'), ('net', '/fr/', 'block')),
listed(k) AS (VALUES {listed}),
hosts AS (SELECT DISTINCT host FROM p),
bad AS (SELECT DISTINCT host FROM hosts, listed WHERE host = k OR ends_with(host, '.' || k)),
best AS (
  SELECT page_id, host, path,
         (SELECT max_by(h || q, length(h || q)) FROM rules WHERE (host = h OR ends_with(host, '.' || h)) AND starts_with(path, q)) AS rule,
         (SELECT max_by(v, length(h || q)) FROM rules WHERE (host = h OR ends_with(host, '.' || h)) AND starts_with(path, q)) AS v
  FROM p)
SELECT page_id, host, path, rule,
       coalesce(v, CASE WHEN host IN (SELECT host FROM bad) THEN 'block' ELSE 'allow' END) AS verdict
FROM best"""


def op10_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wsig.llm.pii import find_pii

    return find_pii(_table(spark, sf_dir, "documents"))


def op6_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from wsig.llm.token_file import token_files

    return token_files(_table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op4_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wsig.llm.substring_dedup import substring_dedup

    return substring_dedup(_table(spark, sf_dir, "documents")).select("doc_id", "n_words", "n_removed", "kept_sha256")


def op9_piece_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from wsig.llm.piece_codec import encode_pieces

    return encode_pieces(_table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"))


def op7_vector_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wsig.llm.vector_search import nearest

    return nearest(_table(spark, sf_dir, "embeddings"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_quality_rules, op2_weak_label, op3_simhash_dedup, op4_substring_dedup, op5_mixing, op6_token_files, op7_vector_search, op8_url_filter, op9_piece_codec, op10_pii)}


def oracle_sql() -> dict[str, str]:
    return {"op8_url_filter": _op8_sql()}
