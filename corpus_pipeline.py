"""The training-data pipeline: toxicity, exact and near duplicates, contamination, packing.

Every stage reads what its predecessor wrote and returns it filtered, with the columns of documents; the
last returns one row per packed piece.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from mvspark.llm import decontaminate, exact_dedup, packing, simhash, toxicity
from mvspark.llm.common import shared_path, table


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Labelled examples come from the table ``labels``; documents scoring 0.5 or more go."""
    return toxicity.drop_toxic(docs, table(spark, sf_dir, "labels"))


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of texts equal but for white space the longest, then the smallest doc_id, stays."""
    return exact_dedup.drop_exact_duplicates(docs)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each component of texts of five-word Jaccard similarity 0.8 the smallest doc_id stays."""
    return simhash.drop_near_duplicates(docs, shingle=5, similar=0.8)


def clean(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with any ten-word window of a benchmark item go."""
    return decontaminate.drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents left, in as few sequences of 1024 tokens as the search finds."""
    placed, _ = packing.pack(docs)
    return placed.drop("part", "nth")


STAGES = [
    ("toxicity", drop_toxic),
    ("exact_dedup", exact),
    ("simhash_dedup", near),
    ("decontamination", clean),
    ("packing", pack),
]

#: toxicity, near duplicates and packing cannot be said in SQL; tests hold the pipeline against brute force
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        path = shared_path(spark, f"pipeline-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
