"""The registered queries of the corpus operators: each applies one operator to its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from pushwave.llm import decontaminate, language, licenses, line_dedup, maxent_lm, order_minhash, packing, quality, simhash, token_store
from pushwave.llm.common import documents
from pushwave.llm.wordpieces import vocabulary_path

Query = Callable[[SparkSession, str], DataFrame]


def op1_order_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return order_minhash.edit_report(documents(spark, sf_dir))


def op2_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.find_leaks(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def op3_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicate_classes(documents(spark, sf_dir))
    return found.select("doc_id", simhash.hex_of("fp").alias("fingerprint"), "component_id")


def op4_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    store = token_store.write_store(documents(spark, sf_dir), vocabulary_path(), end_id=1)
    return token_store.read_store(store, spark)


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.line_digest(documents(spark, sf_dir))


def op6_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language.language_predictions(documents(spark, sf_dir, "doc_id", "text", "lang"))


def op7_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality_scores(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op8_maxent_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return maxent_lm.score_documents(documents(spark, sf_dir))


def op9_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(documents(spark, sf_dir)).drop("findings")


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(documents(spark, sf_dir), vocabulary_path(), end_id=2)


def queries() -> dict[str, Query]:
    own = (op1_order_minhash, op2_decontaminate, op3_simhash, op4_token_store, op5_line_dedup, op6_language_id, op7_quality, op8_maxent_lm, op9_license_scan, op10_packing)
    return {f.__name__: f for f in own}


def oracle_sql() -> dict[str, str]:
    return {"op5_line_dedup": line_dedup.LINE_DEDUP_SQL}
