"""The corpus pipeline: STAGES in order, each written as Parquet and read again for the next."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from pushwave.llm import decontaminate, line_dedup, packing, quality, simhash
from pushwave.llm.common import prepare
from pushwave.llm.wordpieces import vocabulary_path
from pushwave.plans.durable import cut


def good_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier accepts."""
    return quality.keep_good(docs, prepare(spark).read.parquet(f"{sf_dir}/labels.parquet"))


def distinct_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the lines that the corpus repeats; none is dropped."""
    prepare(spark)
    return line_dedup.drop_repeated_lines(docs)


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates: fingerprints within 2 bits, or five-word shingles with a Jaccard similarity from 0.8."""
    prepare(spark)
    return simhash.keep_one_similar(docs)


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item."""
    return decontaminate.drop_leaky(docs, prepare(spark).read.parquet(f"{sf_dir}/benchmark.parquet"))


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the remaining documents in windows of tokens."""
    prepare(spark)
    return packing.pack(docs, vocabulary_path(), end_id=2)


STAGES = [
    ("quality classifier", good_documents),
    ("line dedup", distinct_lines),
    ("SimHash near-dedup", one_of_each),
    ("benchmark decontamination", without_benchmark),
    ("packing", packed),
]
#: The stages learn models and hash texts, which SQL can't express; tests hold them against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = prepare(spark).read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = cut(stage(spark, docs, sf_dir), f"stage-{name.split()[0]}")
    return docs
