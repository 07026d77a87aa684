"""Exact duplicates by a tree merge of sorted digest runs (DataFrame functions only).

Every input partition makes one run: its distinct digests in order, each with the best row of
its group, the group's size so far and a second hash of the text. Runs then meet in rounds of
``fan_in``: runs r*fan_in .. r*fan_in+fan_in-1 become run r, merging equal digests. A merge keeps
the best row and checks that all texts under a digest have one second hash and one length, so
a collision of digests stops the job instead of joining different texts. Only digests travel,
at most one row per digest and run; texts never move.

Defined results: null text counts as empty; empty texts are equal to each other; of equal texts
the row with most code points, then smallest doc_id (null ids last) stays; rows that repeat
both doc_id and text (but for white space) share one verdict, as doc_id names the row that stays; an empty table gives an empty result; other columns
are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WHITE, text_of, written

FAN_IN = 16


def digests(docs: DataFrame) -> DataFrame:
    """(doc_id, digest, check, points, run): one row per document, from one scan of the texts."""
    bare = docs.select(docs["doc_id"].alias("doc_id"), text_of(docs).alias("t"))
    bare = bare.select("doc_id", F.char_length("t").alias("points"), F.translate("t", WHITE, "").alias("t"))
    return bare.select(
        "doc_id",
        F.unhex(F.sha2("t", 256)).alias("digest"),
        F.struct(F.xxhash64("t"), F.length("t")).alias("check"),
        "points",
        F.spark_partition_id().alias("run"),
    )


def _merge(runs: DataFrame) -> DataFrame:
    out = runs.groupBy("digest", "run").agg(
        F.min("best").alias("best"), F.sum("size").alias("size"), F.min("low").alias("low"), F.max("high").alias("high")
    )
    same = F.when(F.col("low") == F.col("high"), F.col("low")).otherwise(
        F.raise_error(F.lit("two texts share a SHA-256 digest"))
    )
    return out.select("digest", "run", "best", "size", same.alias("low"), same.alias("high")).sortWithinPartitions("digest")


def merge_runs(rows: DataFrame, fan_in: int = FAN_IN) -> DataFrame:
    """Groups (digest, keep_id, group_size) of ``digests`` rows, by rounds of multiway merges."""
    top = rows.agg(F.max("run")).first()[0] or 0
    order = F.struct(-F.col("points").cast("long"), F.col("doc_id").isNull(), F.col("doc_id"))
    runs = rows.select(
        "digest", "run", order.alias("best"), F.lit(1).cast("long").alias("size"),
        F.col("check").alias("low"), F.col("check").alias("high"),
    )
    while True:
        runs = runs.withColumn("run", F.floor(F.col("run") / fan_in).cast("int"))
        runs, top = _merge(runs), top // fan_in
        if not top:
            break
    return runs.select("digest", F.col("best.doc_id").alias("keep_id"), F.col("size").alias("group_size"))


def exact_duplicates(docs: DataFrame, fan_in: int = FAN_IN) -> DataFrame:
    """One row per row of ``docs``: doc_id, keep_id, group_size, kept, text_sha256."""
    rows = written(digests(docs), "digests")
    out = rows.select("doc_id", "digest").join(merge_runs(rows, fan_in), "digest")
    return out.select(
        "doc_id", "keep_id", "group_size",
        F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )


def drop_exact_duplicates(docs: DataFrame, fan_in: int = FAN_IN) -> DataFrame:
    """The rows of ``docs`` that stay, with their columns, which travel as one so that no name can clash."""
    lost = exact_duplicates(docs, fan_in).where("not kept").select(
        F.col("doc_id").alias("gone_id"), F.unhex("text_sha256").alias("gone_digest")
    ).distinct()
    rows = docs.select(
        F.struct(*(docs[c] for c in docs.columns)).alias("row"), docs["doc_id"].alias("id"),
        F.unhex(F.sha2(F.translate(text_of(docs), WHITE, ""), 256)).alias("own"),
    )
    left = rows.join(lost, rows["id"].eqNullSafe(lost["gone_id"]) & (rows["own"] == lost["gone_digest"]), "left_anti")
    return left.select(*(F.col("row").getField(c).alias(c) for c in docs.columns))


SQL = r"""
WITH d AS (
  SELECT doc_id, coalesce(text, '') AS t,
         sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g')) AS h
  FROM documents),
g AS (
  SELECT h, count(*) AS group_size, first(doc_id ORDER BY length(t) DESC, doc_id) AS keep_id FROM d GROUP BY h)
SELECT d.doc_id, g.keep_id, g.group_size, d.doc_id = g.keep_id AS kept, d.h AS text_sha256
FROM d JOIN g USING (h)
"""
