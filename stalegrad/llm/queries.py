"""Registered queries of the text operators, with production parameters, on whole tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stalegrad.llm import decontaminate, exact_dedup, language_id, license_scan, minhash_dedup, sharding, substring_dedup, suffix_dedup, tokens


def _docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan_licenses(_docs(spark, sf_dir))


def op2_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash_dedup.near_duplicates(_docs(spark, sf_dir), size=3, percent=85)


def op3_stratified_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = sharding.stratified_shards(_docs(spark, sf_dir), n_shards=8, seed=17)
    return placed.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "source")


def op4_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.remove_repeats(_docs(spark, sf_dir), window=50).drop("kept_text")


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    lengths = tokens.token_lengths(_docs(spark, sf_dir).select("text"), tokens.tokenizer_path())
    return tokens.length_histogram(lengths)


def op6_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.leaks(_docs(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def op7_suffix_array_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.remove_repeats(_docs(spark, sf_dir), width=400).drop("kept_bytes")


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.identify(_docs(spark, sf_dir))


def op9_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokens.pack(_docs(spark, sf_dir), tokens.tokenizer_path(), limit=1024, end_id=2)


def op10_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_groups(_docs(spark, sf_dir))


OP10_SQL = r"""
WITH t AS (
  SELECT CAST(doc_id AS BIGINT) AS doc_id, sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g')) AS text_sha256 FROM documents
), g AS (
  SELECT text_sha256, min(doc_id) AS keep_id, count(*) AS group_size FROM t GROUP BY text_sha256
)
SELECT t.doc_id, g.keep_id, g.group_size, t.doc_id = g.keep_id AS kept, t.text_sha256 FROM t JOIN g USING (text_sha256)
"""


QUERIES = (
    op1_license_scan,
    op2_minhash_near_dedup,
    op3_stratified_shards,
    op4_substring_dedup,
    op5_token_counts,
    op6_benchmark_decontamination,
    op7_suffix_array_dedup,
    op8_language_id,
    op9_best_fit_packing,
    op10_exact_dedup,
)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in QUERIES}


def oracle_sql() -> dict[str, str]:
    return {"op10_exact_dedup": OP10_SQL}
