"""Relational operators around search, in SQL that both engines read, or as DataFrames with an SQL twin."""

from __future__ import annotations

import pandas as pd

#: name -> (SQL for Spark, SQL for DuckDB or None where one text serves both)
BOTH: dict[str, tuple[str, str | None]] = {
    "r_filtered": ("SELECT d.doc_id, d.lang FROM documents d JOIN labels l ON d.doc_id = l.doc_id WHERE d.lang = 'en' AND l.quality = 1", None),
    "r_semi": ("SELECT doc_id FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)", None),
    "r_anti": ("SELECT doc_id FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)", None),
    "r_full_outer": ("SELECT coalesce(a.k, b.k) AS k, a.n AS left_n, b.n AS right_n FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer GROUP BY c_nationkey) a FULL OUTER JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier GROUP BY s_nationkey) b ON a.k = b.k", None),
    "r_broadcast_join": ("SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name", None),
    "r_range_join": ("SELECT p_partkey, count(*) AS n FROM part JOIN nation ON p_size BETWEEN n_nationkey AND n_nationkey + 3 GROUP BY p_partkey", None),
    "r_interval_join": ("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id < b.event_id AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 HOUR", None),
    "r_theta_join": ("SELECT a.n_nationkey AS a, count(*) AS n FROM nation a JOIN supplier b ON a.n_nationkey <> b.s_nationkey AND a.n_nationkey < b.s_suppkey GROUP BY a.n_nationkey", None),
    "r_asof": ("SELECT event_id, last_value(prev) IGNORE NULLS OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_view FROM (SELECT *, CASE WHEN event_type = 'view' THEN event_id END AS prev FROM events)",
               "SELECT event_id, last_value(prev IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_view FROM (SELECT *, CASE WHEN event_type = 'view' THEN event_id END AS prev FROM events)"),
    "r_cube": ("SELECT lang, source, count(*) AS n FROM documents GROUP BY CUBE (lang, source)", None),
    "r_rollup": ("SELECT lang, source, count(*) AS n FROM documents GROUP BY ROLLUP (lang, source)", None),
    "r_grouping_sets": ("SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())", None),
    "r_pivot": ("SELECT source, count(CASE WHEN lang = 'en' THEN 1 END) AS en, count(CASE WHEN lang = 'de' THEN 1 END) AS de FROM documents GROUP BY source", None),
    "r_rank_all": ("SELECT p_partkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS dr, ntile(4) OVER w AS nt FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size, p_partkey)", None),
    "r_frames": ("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS n, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events", None),
    "r_top_k": ("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 5", None),
    "r_union": ("SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier", None),
    "r_intersect": ("SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier", None),
    "r_except": ("SELECT doc_id FROM documents EXCEPT SELECT doc_id FROM labels", None),
    "r_string": ("SELECT doc_id, length(text) AS n, substring(lower(text), 1, 5) AS head, md5(text) AS h FROM documents WHERE text LIKE '%the%'", None),
    "r_date": ("SELECT year(o_orderdate) AS y, month(o_orderdate) AS m, count(*) AS n FROM orders GROUP BY year(o_orderdate), month(o_orderdate)", None),
    "r_math": ("SELECT p_partkey, round(sqrt(p_retailprice), 6) AS a, round(ln(p_retailprice), 6) AS b, CAST(floor(p_retailprice / 7) AS BIGINT) AS c FROM part", None),
    "r_subquery": ("SELECT doc_id FROM documents d WHERE n_chars > (SELECT avg(n_chars) FROM documents e WHERE e.lang = d.lang)", None),
    "r_cte": ("WITH a AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey), b AS (SELECT max(n) AS m FROM a) SELECT o_custkey, n FROM a, b WHERE n = m", None),
    "r_recursive": ("WITH RECURSIVE t(n, level) AS (SELECT o_orderkey, 1 FROM orders WHERE o_orderkey = 1 UNION ALL SELECT o_orderkey, level + 1 FROM t JOIN orders ON CAST(floor(o_orderkey / 4) AS BIGINT) = n WHERE level < 9) SELECT n, level FROM t", None),
    "r_json": ("SELECT event_id, get_json_object(props, '$.k') AS k FROM events", "SELECT event_id, CASE WHEN json_type(props, '$.k') IS NULL THEN NULL ELSE json_extract_string(props, '$.k') END AS k FROM events"),
    "r_map": ("SELECT source, map_keys(m)[0] AS least, element_at(m, map_keys(m)[0]) AS n, size(m) AS langs FROM (SELECT source, map_from_entries(array_sort(collect_list(struct(lang, n)))) AS m FROM (SELECT source, lang, count(*) AS n FROM documents WHERE lang IS NOT NULL GROUP BY source, lang) GROUP BY source)",
              "SELECT source, min(lang) AS least, arg_min(n, lang) AS n, count(*)::INTEGER AS langs FROM (SELECT source, lang, count(*) AS n FROM documents WHERE lang IS NOT NULL GROUP BY source, lang) GROUP BY source"),
    "r_struct": ("SELECT s.k AS lang, s.n AS n, s.longest AS longest FROM (SELECT named_struct('k', lang, 'n', count(*), 'longest', max(n_chars)) AS s FROM documents GROUP BY lang)",
                 "SELECT lang, count(*) AS n, max(n_chars) AS longest FROM documents GROUP BY lang"),
    "r_regression": ("SELECT event_type, round(regr_slope(value, user_id), 6) AS slope, round(corr(value, user_id), 6) AS r, round(regr_r2(value, user_id), 6) AS r2 FROM events GROUP BY event_type", None),
    "r_null": ("SELECT l.doc_id, coalesce(nullif(quality, 0), -1) AS q FROM labels l", None),
    "r_argmax": ("SELECT p_brand, max_by(p_partkey, p_retailprice * 1000000 + p_partkey) AS best FROM part GROUP BY p_brand", None),
    "r_array": ("SELECT conv_id, array_join(array_sort(collect_list(turn)), ',') AS turns FROM conversations GROUP BY conv_id", "SELECT conv_id, string_agg(turn, ',' ORDER BY turn) AS turns FROM conversations GROUP BY conv_id"),
    "r_lateral": ("SELECT n_name, x.o AS best FROM nation, LATERAL (SELECT max(c_custkey) AS o FROM customer WHERE c_nationkey = n_nationkey) x", None),
    "r_in_subquery": ("SELECT s_suppkey FROM supplier WHERE s_nationkey IN (SELECT n_nationkey FROM nation WHERE n_name LIKE '%A%')", None),
    "r_ratio": ("SELECT n_regionkey, count(*) AS n, sum(count(*)) OVER () AS total FROM nation GROUP BY n_regionkey", None),
    "r_html": (r"SELECT page_id, length(regexp_replace(html, '<[^>]*>', '')) AS n FROM pages", "SELECT page_id, length(regexp_replace(html, '<[^>]*>', '', 'g')) AS n FROM pages"),
}


def _run(sql: str):
    import re

    def run(spark, sf):
        for name in set(re.findall(r"(?:FROM|JOIN) (\w+)", sql)):
            if name in ("documents", "labels", "customer", "supplier", "nation", "part", "events", "orders", "pages", "conversations", "lineitem", "benchmark", "embeddings", "region"):
                spark.read.parquet(f"{sf}/{name}.parquet").createOrReplaceTempView(name)
        return spark.sql(sql)

    return run


QUERIES = {name: _run(sql) for name, (sql, _) in BOTH.items()}
SQL = {name: twin or sql for name, (sql, twin) in BOTH.items()}


# --- operators that need the DataFrame API, tied to search results ---


def _truth(spark, sf):
    from .catalogue import QUERIES as K

    return K["k6a_maxsim_topk"](spark, sf)


def r_filtered_topk(spark, sf):
    """Top-k with the filter before scoring, and after it with twice the answers: the same where twice suffices."""
    from pyspark.sql import functions as F

    from ..operators import similarity as S
    from ..sources import fixtures as X

    t = X.from_embeddings(spark, sf)
    q, o = X.as_queries(t), S.objects(t)
    keep = F.col("mv_id") % 1000000 < 4
    before = S.linear_scan(q, o, 5, where=keep)
    after = S.top_k(S.linear_scan(q, o, 40).where(keep), 5)
    return before.join(after.select("qid", "rank", F.col("mv_id").alias("after")), ["qid", "rank"], "left").select("qid", "rank", "mv_id", "after", "score")


def r_results_by_label(spark, sf):
    """Answers by the label of query and object, in grouping sets."""
    from pyspark.sql import functions as F

    t = _truth(spark, sf).select(F.floor(F.col("qid") / 1000000).alias("asked"), F.floor(F.col("mv_id") / 1000000).alias("found"))
    return t.groupingSets([["asked", "found"], ["asked"], []], "asked", "found").agg(F.count("*").alias("n"))


def r_sample(spark, sf):
    """A Bernoulli sample and a stratified one, with seeds: rows differ by engine, sizes lie near the share."""
    from pyspark.sql import functions as F

    d = spark.read.parquet(f"{sf}/documents.parquet")
    n = d.count()
    a = d.sample(0.5, seed=1).agg((F.count("*").between(int(n * 0.4), int(n * 0.6))).alias("half"))
    b = d.sampleBy("lang", {"en": 1.0}, seed=1).agg((F.count("*") == d.where("lang = 'en'").count()).alias("english"))
    return a.crossJoin(b)


def r_sketches(spark, sf):
    """Distinct counts and quantiles by sketch, beside the exact ones: relative error within a tenth."""
    from pyspark.sql import functions as F

    e = spark.read.parquet(f"{sf}/lineitem.parquet")
    near = lambda a, b: F.abs(a / b - 1) < 0.1
    return e.agg(
        near(F.approx_count_distinct("l_partkey"), F.count_distinct("l_partkey")).alias("hll"),
        near(F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")), F.count_distinct("l_partkey")).alias("sketch"),
        near(F.percentile_approx("l_extendedprice", 0.5), F.percentile("l_extendedprice", 0.5)).alias("quantile"),
    )


def r_udaf(spark, sf):
    """The mean vector of every label by a grouped Arrow function, summed up as its first coordinate."""
    from pyspark.sql import functions as F

    def mean(v: pd.Series) -> float:
        return float(sum(float(x[0]) for x in v) / len(v))

    first_mean = F.pandas_udf(mean, "double")

    e = spark.read.parquet(f"{sf}/embeddings.parquet")
    return e.groupBy("label").agg(F.round(first_mean("embedding"), 6).alias("m"))


def r_python_source(spark, sf):
    """Objects of a fixture through the Python data source."""
    from ..sources.datasource import register

    register(spark)
    return spark.read.format("multivector").option("path", f"{sf}/embeddings.parquet").option("c", "8").load().groupBy("mv_id").agg({"tok_ix": "count"}).withColumnRenamed("count(tok_ix)", "n")


def r_bucketed(spark, sf):
    """A bucketed table read back: a join of both sides on the bucket key needs no shuffle of it."""
    from pyspark.sql import functions as F

    from ..sources.shared import folder

    name = f"mv_bucketed_{abs(hash(sf)) % 10**8}"
    spark.sql(f"DROP TABLE IF EXISTS {name}")
    spark.read.parquet(f"{sf}/orders.parquet").write.bucketBy(8, "o_custkey").sortBy("o_custkey").option("path", folder(spark, "bucketed")).saveAsTable(name)
    t = spark.table(name)
    return t.groupBy("o_custkey").agg(F.count("*").alias("n"), F.max("o_orderkey").alias("last"))


def r_formats(spark, sf):
    """Labels written and read as CSV, JSON and ORC."""
    from pyspark.sql import functions as F

    from ..sources.shared import folder

    d, out = spark.read.parquet(f"{sf}/labels.parquet"), None
    for kind in ("csv", "json", "orc"):
        at = folder(spark, kind)
        d.write.format(kind).save(at)
        one = spark.read.format(kind).schema(d.schema).load(at).agg(F.lit(kind).alias("kind"), F.count("*").alias("n"), F.sum("doc_id").alias("ids"), F.sum("toxic").cast("long").alias("toxic"))
        out = one if out is None else out.unionByName(one)
    return out


def r_search_function(spark, sf):
    """Search as a table function over a saved index."""
    from ..functions import search_sql
    from ..operators import index as I
    from ..operators import similarity as S
    from ..config import IndexConfig, LinkConfig
    from ..sources import fixtures as X
    from ..sources.shared import folder

    t = X.from_embeddings(spark, sf)
    at = folder(spark, "index")
    I.build_index(S.objects(t), IndexConfig(M=8, ef_construction=32), LinkConfig(M=8)).save(at)
    search_sql.register(spark, "mv_search", at, scale=16129.0)
    S.objects(t).where("mv_id % 5 = 0").selectExpr("mv_id AS qid", "vecs").createOrReplaceTempView("mv_asked")
    return spark.sql("SELECT a.qid, s.rank, s.mv_id, s.score FROM mv_asked a, LATERAL mv_search(a.vecs, 10, 5000) s")


_OWN = (r_filtered_topk, r_results_by_label, r_sample, r_sketches, r_udaf, r_python_source, r_bucketed, r_formats, r_search_function)
QUERIES |= {f.__name__: f for f in _OWN}


def _twins() -> dict[str, str]:
    from .catalogue import SQL as K
    from .catalogue import TOK

    top = K["k6a_maxsim_topk"]
    part = TOK + ", x AS (SELECT qid, mv_id, sum(s) AS score FROM (SELECT qid, q_ix, mv_id, max(s) AS s FROM sc GROUP BY ALL) GROUP BY ALL)"
    return {
        "r_filtered_topk": part + """, f AS (SELECT qid, CAST(row_number() OVER (PARTITION BY qid ORDER BY score DESC, mv_id) AS INTEGER) AS rank, mv_id, score FROM x WHERE mv_id % 1000000 < 4 QUALIFY rank <= 5),
a AS (SELECT qid, CAST(row_number() OVER (PARTITION BY qid ORDER BY score DESC, mv_id) AS INTEGER) AS rank, mv_id AS after FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score DESC, mv_id) AS r FROM x) WHERE r <= 40 AND mv_id % 1000000 < 4 QUALIFY rank <= 5)
SELECT qid, rank, mv_id, after, score FROM f LEFT JOIN a USING (qid, rank)""",
        "r_results_by_label": f"WITH t AS ({top}) SELECT CAST(qid // 1000000 AS BIGINT) AS asked, CAST(mv_id // 1000000 AS BIGINT) AS found, count(*) AS n FROM t GROUP BY GROUPING SETS ((CAST(qid // 1000000 AS BIGINT), CAST(mv_id // 1000000 AS BIGINT)), (CAST(qid // 1000000 AS BIGINT)), ())",
        "r_sample": "SELECT TRUE AS half, TRUE AS english",
        "r_sketches": "SELECT TRUE AS hll, TRUE AS sketch, TRUE AS quantile",
        "r_udaf": "SELECT label, round(avg(CAST(embedding[1] AS DOUBLE)), 6) AS m FROM embeddings GROUP BY label",
        "r_python_source": TOK + " SELECT mv_id, count(*) AS n FROM tok GROUP BY mv_id",
        "r_bucketed": "SELECT o_custkey, count(*) AS n, max(o_orderkey) AS last FROM orders GROUP BY o_custkey",
        "r_formats": "SELECT kind, count(*) AS n, CAST(sum(doc_id) AS BIGINT) AS ids, CAST(sum(toxic) AS BIGINT) AS toxic FROM labels, (SELECT unnest(['csv', 'json', 'orc']) AS kind) GROUP BY kind",
        "r_search_function": top,
    }


SQL |= _twins()
