"""Shared helpers: table access, written tables in the shared folder, components."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space that separates words: space, tab, line feed, vertical tab, form feed, return
WHITE = " \t\n\x0b\x0c\r"

_written: list[tuple[SparkSession, str]] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_root(spark: SparkSession) -> str:
    """The folder all executors share; a temporary one only where none is set and Spark is local."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if root:
        return root.rstrip("/")
    if not spark.sparkContext.master.startswith(("local[", "local")) or "cluster" in spark.sparkContext.master:
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    root = "file://" + tempfile.mkdtemp(prefix="mvspark-shared-")
    spark.sparkContext.setCheckpointDir(root)
    return shared_root(spark)


def shared_path(spark: SparkSession, label: str) -> str:
    """A new path under the shared folder; what is written there goes when the driver ends."""
    path = f"{shared_root(spark)}/mvspark-{label}-{uuid.uuid4().hex}"
    _written.append((spark, path))
    return path


def written(df: DataFrame, label: str, codec: str = "zstd", by: str | None = None) -> DataFrame:
    """Write a table to the shared folder and read it again: cuts lineage, survives lost executors."""
    spark, path = df.sparkSession, shared_path(df.sparkSession, label)
    to = df.write.option("compression", codec)
    (to.partitionBy(by) if by else to).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def release_all() -> None:
    """Delete every table that this process wrote to the shared folder."""
    while _written:
        spark, path = _written.pop()
        try:
            jvm = spark.sparkContext._jvm
            at = jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)
        except Exception:  # the JVM may be gone at exit
            return


atexit.register(release_all)


def text_of(df: DataFrame, column: str = "text") -> Column:
    """The text, null as empty."""
    return F.coalesce(df[column].cast("string"), F.lit(""))


def without(docs: DataFrame, gone: DataFrame) -> DataFrame:
    """The rows of ``docs`` but for those of ``gone`` (doc_id, check), with their columns; check is the text's xxhash64.

    The columns travel as one, so that none can clash with a name used here.
    """
    rows = docs.select(F.struct(*(docs[c] for c in docs.columns)).alias("row"), docs["doc_id"].cast("long").alias("id"), F.xxhash64(text_of(docs)).alias("own"))
    lost = gone.select(F.col("doc_id").alias("gone_id"), F.col("check").alias("gone_check")).distinct()
    left = rows.join(lost, rows["id"].eqNullSafe(lost["gone_id"]) & (rows["own"] == lost["gone_check"]), "left_anti")
    return left.select(*(F.col("row").getField(c).alias(c) for c in docs.columns))


#: a key that more than one in so many rows share is joined by broadcast, so at most as many keys are
HEAVY = 1000
#: rows of a key up to which a task takes them anyway
PLENTY = 2000


def spread_join(many: DataFrame, one: DataFrame, on: list[str], count: str, how: str = "inner") -> DataFrame:
    """``many`` joined with ``one``, which has one row a key and in ``count`` the key's rows in ``many``.

    Keys with more than a thousandth of all rows, so a thousand at most, go by broadcast and their rows stay
    where they are; the rest meet by shuffle. No task gets all rows of a frequent key.
    """
    total = one.agg(F.sum(count)).first()[0] or 0
    floor = max(total // HEAVY, PLENTY)
    heavy = one.where(F.col(count) > floor)
    if not one.agg(F.max(count)).first()[0] or not heavy.limit(1).count():
        return many.join(one, on, how)
    light = one.where(F.coalesce(F.col(count), F.lit(0)) <= floor)
    keys = F.broadcast(heavy.select(*on))
    same = lambda a, b: [a[c].eqNullSafe(b[c]) for c in on]
    few = many.join(F.broadcast(heavy), on, "inner")
    rest = many.join(keys, same(many, keys), "left_anti").join(light, on, how)
    return few.unionByName(rest.select(few.columns))


def components(edges: DataFrame, label: str = "cc", rounds: int = 60) -> DataFrame:
    """Connected components of ``edges(a long, b long)`` by alternating star contractions.

    Returns (v, root): each vertex with an edge and the smallest vertex it reaches. Every round
    replaces edges by edges to the smallest neighbour, so the edge count never grows, and is
    written to the shared folder; the driver reads one row a round.
    """
    e = written(
        edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct(), label
    )
    state = None
    for _ in range(rounds):
        both = e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.join(low, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        down = large.groupBy("a").agg(F.min("b").alias("m"))
        pairs = large.join(down, "a")
        small = (
            pairs.where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
            .unionByName(down.select("a", F.col("m").alias("b")))
            .distinct()
        )
        e = written(small, label)
        now = e.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if state == tuple(now):
            break
        state = tuple(now)
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    roots = e.select(F.col("a").alias("v"), F.col("b").alias("root"))
    return roots.unionByName(e.select(F.col("b").alias("v"), F.col("b").alias("root")).distinct())
