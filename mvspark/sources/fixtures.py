"""Multi-vector datasets from the given tables."""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.vectors import quantise, sign_vector


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def from_embeddings(spark: SparkSession, sf_dir: str, c: int = 8) -> DataFrame:
    """Tokens of objects of c vectors of one label, as whole numbers; objects of one token dropped."""
    e = read(spark, sf_dir, "embeddings")
    w = Window.partitionBy("label").orderBy("vec_id")
    t = e.select("label", (F.row_number().over(w) - 1).alias("i"), quantise(F.col("embedding")).alias("vec"))
    t = t.select((F.col("label") * 1000000 + F.floor(F.col("i") / c)).cast("long").alias("mv_id"), (F.col("i") % c).alias("tok_ix"), "vec")
    return t.withColumn("n", F.count("*").over(Window.partitionBy("mv_id"))).where("n >= 2").drop("n")


def words_of(spark: SparkSession, sf_dir: str, table: str = "documents", key: str = "doc_id") -> DataFrame:
    """(mv_id, word) of all words of all texts of two words or more, lower-cased, repeats included."""
    w = F.filter(F.split(F.lower("text"), r"\s+"), lambda x: x != "")
    t = read(spark, sf_dir, table).select(F.col(key).cast("long").alias("mv_id"), w.alias("w")).where(F.size("w") >= 2)
    return t.select("mv_id", F.explode("w").alias("word"))


def word_objects(spark: SparkSession, sf_dir: str, table: str = "documents", key: str = "doc_id", d: int = 128) -> DataFrame:
    """Tokens of whole texts: each different word of a text is a token, in alphabetic order."""
    w = words_of(spark, sf_dir, table, key).distinct()
    w = w.withColumn("tok_ix", F.row_number().over(Window.partitionBy("mv_id").orderBy("word")) - 1)
    vec = w.select("word").distinct().withColumn("vec", sign_vector(F.col("word"), d))
    return w.join(vec, "word").select("mv_id", "tok_ix", "word", "vec")


def containing(texts: DataFrame, passages: DataFrame) -> DataFrame:
    """(qid, mv_id) of texts (mv_id, text) that hold a passage (qid, passage), each text looked at once with all passages at hand."""
    rows = [(r.qid, r.passage) for r in passages.where("passage is not null").collect()]
    if sum(len(p) for _, p in rows) > PASSAGES:
        raise ValueError(f"the passages hold more than {PASSAGES} characters; search them in parts")

    def run(batches):
        for b in batches:
            hit = [(q, i) for i, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist()) if t for q, p in rows if p in t]
            yield pa.RecordBatch.from_arrays([pa.array([q for q, _ in hit], pa.int64()), pa.array([i for _, i in hit], pa.int64())], names=["qid", "mv_id"])

    return texts.select("mv_id", "text").mapInArrow(run, "qid long, mv_id long")


#: characters of passages that every task may hold
PASSAGES = 50_000_000


def from_documents(spark: SparkSession, sf_dir: str, n_words: int = 32, d: int = 128, table: str = "documents", key: str = "doc_id", skip: int = 0) -> DataFrame:
    """Tokens of the first words of each text; objects of one token dropped."""
    t = read(spark, sf_dir, table).select(F.col(key).alias("mv_id"), F.filter(F.split(F.lower("text"), r"\s+"), lambda x: x != "").alias("w"))
    t = t.select("mv_id", F.slice("w", skip + 1, n_words).alias("w")).where(F.size("w") >= 2)
    t = t.select("mv_id", F.posexplode("w").alias("tok_ix", "word"))
    vec = t.select("word").distinct().withColumn("vec", sign_vector(F.col("word"), d))
    return t.join(vec, "word").select("mv_id", "tok_ix", "word", "vec")


_WHITE = re.compile("[ \t\n\x0b\f\r]+")


def _signs(word: str, d: int) -> np.ndarray:
    """+1 or -1 for each bit of salted md5 digests of a word."""
    raw = b"".join(hashlib.md5(f"{word}#{b}".encode("utf-8", "surrogatepass")).digest() for b in range(-(-d // 128)))
    return np.unpackbits(np.frombuffer(raw, np.uint8)).astype(np.int8)[:d] * np.int8(2) - np.int8(1)


def from_windows(spark: SparkSession, sf_dir: str, c: int = 32, d: int = 128, table: str = "documents", key: str = "doc_id", keep: int = 100_000) -> DataFrame:
    """Tokens of whole texts: each is cut into c windows of equal word counts (one word each, if there are fewer words).

    A window is the sum of its words' sign vectors, scaled to unit length and then to whole numbers (127 to a unit), so
    that scores are exact in any engine. Texts of one word are dropped. A worker keeps the vectors of ``keep`` words.
    """
    rows = read(spark, sf_dir, table).select(F.col(key).cast("long").alias("mv_id"), F.lower("text").alias("text"))

    def run(batches):
        known: dict[str, np.ndarray] = {}
        for b in batches:
            for lo in range(0, b.num_rows, 200):
                some = b.slice(lo, 200)
                ids, places, sums = [], [], []
                for i, t in zip(some.column(0).to_pylist(), some.column(1).to_pylist()):
                    w = [x for x in _WHITE.split(t or "") if x]
                    if len(w) < 2:
                        continue
                    n = min(c, len(w))
                    if len(known) > keep:
                        known.clear()
                    for x in w:
                        if x not in known:
                            known[x] = _signs(x, d)
                    first = -(-np.arange(n) * len(w) // n)
                    ids += [i] * n
                    places += range(n)
                    sums.append(np.add.reduceat(np.stack([known[x] for x in w]), first, axis=0, dtype=np.int64))
                x = np.concatenate(sums).astype(np.float64) if sums else np.zeros((0, d))
                size = np.sqrt((x * x).sum(1))
                v = np.where(size[:, None] > 0, np.floor(x / np.maximum(size, 1e-300)[:, None] * 127 + 0.5), 0)
                lists = pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * d), pa.array(v.ravel()))
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(places, pa.int32()), lists], names=["mv_id", "tok_ix", "vec"])

    return rows.mapInArrow(run, "mv_id long, tok_ix int, vec array<double>")


def as_queries(tokens: DataFrame, every: int = 5) -> DataFrame:
    """Every so-manieth object as a query."""
    return tokens.where(F.pmod("mv_id", F.lit(every)) == 0).select(F.col("mv_id").alias("qid"), F.col("tok_ix").alias("q_ix"), "vec")


def from_orders(spark: SparkSession, sf_dir: str, d: int = 128) -> DataFrame:
    """Tokens of orders of two lines or more: a line is the sum of the vectors of its five attribute values."""
    p = read(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), "p_brand", "p_type")
    li = read(spark, sf_dir, "lineitem").join(p, "l_partkey")
    feats = {
        "brand": F.col("p_brand"), "type": F.col("p_type"), "quantity": F.floor(F.col("l_quantity") / 10).cast("string"),
        "month": F.date_format("l_shipdate", "yyyy-MM"), "flag": F.col("l_returnflag"),
    }
    # (l_orderkey, l_linenumber) is not unique, so the place comes from an order over all columns
    w = Window.partitionBy("l_orderkey").orderBy(*sorted(li.columns))
    rows = li.select(F.col("l_orderkey").alias("mv_id"), (F.row_number().over(w) - 1).alias("tok_ix"), *(F.concat(F.lit(f"{k}="), v).alias(k) for k, v in feats.items()))
    rows = rows.withColumn("n", F.count("*").over(Window.partitionBy("mv_id"))).where("n >= 2").drop("n")
    for i, k in enumerate(feats):
        vec = rows.select(k).distinct().withColumn("one", sign_vector(F.col(k), d))
        total = F.col("one") if not i else F.zip_with("vec", "one", lambda x, y: x + y)
        rows = rows.join(vec, k).withColumn("vec", total).drop("one")
    return rows.select("mv_id", "tok_ix", "vec")


def from_pages(spark: SparkSession, sf_dir: str, d: int = 128) -> DataFrame:
    """Tokens of pages: a title, heading, paragraph or list item is the sum of its words' vectors."""
    html = F.regexp_extract_all("html", F.lit(r"(?is)<(?:title|h1|p|li)\b[^>]*>(.*?)</(?:title|h1|p|li)>"), 1)
    b = read(spark, sf_dir, "pages").select(F.col("page_id").alias("mv_id"), F.posexplode(html).alias("tok_ix", "block"))
    bare = F.lower(F.regexp_replace("block", "<[^>]*>", " "))
    words = b.select("mv_id", "tok_ix", F.explode(F.split(bare, r"\s+")).alias("word")).where("word <> ''").groupBy("mv_id", "tok_ix", "word").agg(F.count("*").alias("n"))
    vec = words.select("word").distinct().withColumn("vec", sign_vector(F.col("word"), d))
    parts = words.join(vec, "word").select("mv_id", "tok_ix", "n", F.posexplode("vec").alias("at", "x"))
    sums = parts.groupBy("mv_id", "tok_ix", "at").agg(F.sum(F.col("n") * F.col("x")).alias("x"))
    t = sums.groupBy("mv_id", "tok_ix").agg(F.array_sort(F.collect_list(F.struct("at", "x")))["x"].alias("vec"))
    return t.withColumn("k", F.count("*").over(Window.partitionBy("mv_id"))).where("k >= 2").drop("k")
