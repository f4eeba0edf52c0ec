"""From raw documents to packed training sequences, in five stages.

Each stage works on all that its predecessor kept, written as Parquet and read again in between.
"""

from __future__ import annotations

from divknn.llm import decontaminate, jaccard_join, packing, quality, secrets
from divknn.llm.common import saved, table
from divknn.llm.tokens import vocabulary_path
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def reject_bad(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that fail the base rule or a certified cutoff go."""
    return quality.keep_good(docs, table(spark, sf_dir, "labels"))


def one_of_similar(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of similar documents the one of smallest id stays."""
    return jaccard_join.one_per_group(docs)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item go."""
    return decontaminate.drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def hide_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every reported span becomes a mark; ``n_chars`` follows."""
    return secrets.redact(docs).withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs, vocabulary_path())


STAGES = [
    ("quality_rules", reject_bad),
    ("ngram_jaccard_join", one_of_similar),
    ("benchmark_decontamination", drop_leaks),
    ("secret_scan", hide_secrets),
    ("best_fit_packing", pack),
]

#: SQL can express neither the binomial bounds nor the tokenizer; tests/llm/test_pipeline.py has a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = saved(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
