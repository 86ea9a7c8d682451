"""The corpus pipeline: rules, near-duplicates, secrets, mixing and packing, each on what the last one kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from cohort_engine.llm import jaccard_tree, mixing, packing, quality_rules, secrets
from cohort_engine.llm.common import table, work_path
from cohort_engine.session import ship


def reject_low_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rule or the learned list rejects go."""
    ship(spark)
    return quality_rules.keep_documents(docs, table(spark, sf_dir, "labels"))


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near-duplicates (five-word shingles, similarity 0.8) the smallest id stays."""
    ship(spark)
    return jaccard_tree.keep_one_each(docs, percent=80, words=5)


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every secret span becomes a mark."""
    ship(spark)
    return secrets.redact(docs, secrets.train(docs))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Whole documents in the numbers the mix takes; a repeated document is repeated rows."""
    ship(spark)
    return mixing.mixed_documents(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces with their sequences and offsets."""
    ship(spark)
    return packing.pack_documents(docs)


STAGES = [("quality_rules", reject_low_quality), ("jaccard_join", one_of_each_group), ("secret_scan", redact_secrets), ("mixing", mix_sources), ("packing", pack_sequences)]

#: Learned rules and packing cannot be said in SQL; tests/llm/test_pipeline.py holds the filters against a plain Python version, and mixing and packing to their rules.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        path = work_path(spark, f"pipeline_{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
