"""Queries of the training-data operators: name -> (query, DuckDB SQL or None)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shardgraph.llm import decontaminate, html_template, jaccard_join, langid, license_scan, mixing, near_dup, sharding, toxicity, url_filter
from shardgraph.llm.common import table


def op1_near_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dup.near_duplicates(table(spark, sf_dir, "embeddings"), least=0.9)


def op2_page_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_template.extract(table(spark, sf_dir, "pages"))


def op3_shard_by_bytes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.assign_shards(table(spark, sf_dir, "documents"), n_shards=8)


def op4_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.identify(table(spark, sf_dir, "documents"))


def op5_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.filter_urls(table(spark, sf_dir, "pages"))


def op6_shingle_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.similar_components(table(spark, sf_dir, "documents"))


def op7_token_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents"))


def op8_license_notices(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan(table(spark, sf_dir, "documents")).drop("spans")


def op9_toxic_grade(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = toxicity.train(docs, table(spark, sf_dir, "labels"))
    return toxicity.severity(docs, model).select("doc_id", "_toxicity.*", toxicity.rejects().alias("toxic"))


def op10_benchmark_tiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return decontaminate.covered_by(docs, table(spark, sf_dir, "benchmark")).select("doc_id", "_overlap.*", decontaminate.contaminated().alias("contaminated"))


LLM = {
    "op1_near_vectors": (op1_near_vectors, near_dup.ORACLE),
    "op2_page_text": (op2_page_text, None),
    "op3_shard_by_bytes": (op3_shard_by_bytes, None),
    "op4_language": (op4_language, None),
    "op5_url_rules": (op5_url_rules, url_filter.ORACLE),
    "op6_shingle_join": (op6_shingle_join, jaccard_join.ORACLE),
    "op7_token_mix": (op7_token_mix, mixing.oracle()),
    "op8_license_notices": (op8_license_notices, None),
    "op9_toxic_grade": (op9_toxic_grade, None),
    "op10_benchmark_tiles": (op10_benchmark_tiles, None),
}
