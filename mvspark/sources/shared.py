"""Cutting lineage, and folders, where all executors can reach."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def root(spark: SparkSession) -> str:
    """The folder all executors share; a temporary one only where none is set and Spark is local."""
    sc = spark.sparkContext
    at = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if at:
        return at.rstrip("/")
    if not sc.master.startswith("local") or "cluster" in sc.master:
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    sc.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="mvspark-checkpoint-"))
    return sc.getCheckpointDir()


def folder(spark: SparkSession, label: str) -> str:
    """A new path under the shared folder."""
    return f"{root(spark)}/mvspark-{label}-{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    """``df`` checkpointed."""
    sc = df.sparkSession.sparkContext
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(root(df.sparkSession))
    return df.checkpoint()
