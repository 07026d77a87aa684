"""Accuracy and cost measures over result tables."""

from __future__ import annotations

import statistics
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def recall(results: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """(qid, recall): share of the k true answers returned."""
    hit = truth.where(F.col("rank") <= k).select("qid", "mv_id").join(results.where(F.col("rank") <= k).select("qid", "mv_id", F.lit(1).alias("hit")), ["qid", "mv_id"], "left")
    return hit.groupBy("qid").agg((F.coalesce(F.sum("hit"), F.lit(0)) / F.lit(k)).alias("recall"))


def recall_by_score(results: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """As ``recall``, but any answer scoring as high as the k-th true one counts."""
    bar = truth.where(F.col("rank") == k).select("qid", F.col("score").alias("bar"))
    return results.where(F.col("rank") <= k).join(bar, "qid").groupBy("qid").agg((F.sum((F.col("score") >= F.col("bar")).cast("int")) / F.lit(k)).alias("recall"))


def at_target(curve: DataFrame, target: float = 0.9) -> DataFrame:
    """(method, ms): time at which a curve of (method, recall, ms) first reaches the target, interpolated."""
    w = Window.partitionBy("method").orderBy("recall", "ms")
    c = curve.withColumn("r0", F.lag("recall").over(w)).withColumn("m0", F.lag("ms").over(w)).where(F.col("recall") >= target)
    c = c.withColumn("n", F.row_number().over(w)).where("n = 1")
    slope = (F.col("ms") - F.col("m0")) * (F.lit(target) - F.col("r0")) / (F.col("recall") - F.col("r0"))
    return c.select("method", F.when(F.col("r0").isNull(), F.col("ms")).otherwise(F.col("m0") + slope).alias("ms"))


def at_budget(curve: DataFrame, ms: float) -> DataFrame:
    return curve.where(F.col("ms") <= ms).groupBy("method").agg(F.max("recall").alias("recall"))


def speedup(curve: DataFrame, method: str, target: float = 0.9) -> DataFrame:
    """(method, factor): time of each other method at the target recall over that of ``method``; null where it is not reached."""
    t = at_target(curve, target)
    own = t.where(F.col("method") == method).select(F.col("ms").alias("own"))
    every = curve.select("method").distinct().where(F.col("method") != method).join(t, "method", "left")
    return every.crossJoin(own).select("method", (F.col("ms") / F.col("own")).alias("factor"))  # one row on the right


def growth(points: DataFrame) -> DataFrame:
    """Slope and fit of ms over log n."""
    return points.agg(F.regr_slope("ms", F.log("n")).alias("slope"), F.regr_r2("ms", F.log("n")).alias("r2"))


def timed(run: Callable[[], DataFrame], repeats: int = 3, warm: int = 1) -> float:
    """Median seconds of running a query whole, after ``warm`` runs that do not count. Serves searches and builds."""
    took = []
    for i in range(warm + repeats):
        begin = time.perf_counter()
        run().write.format("noop").mode("overwrite").save()
        if i >= warm:
            took.append(time.perf_counter() - begin)
    return statistics.median(took)


def recall_time_curve(runs: list[tuple[str, str, DataFrame, float]], truth: DataFrame, k: int) -> DataFrame:
    """(method, setting, recall, ms) of runs (method, setting, results, ms a query): the points of every method's curve."""
    out = None
    for method, setting, results, ms in runs:
        one = recall(results, truth, k).agg(F.avg("recall").alias("recall"))
        one = one.select(F.lit(method).alias("method"), F.lit(setting).alias("setting"), "recall", F.lit(float(ms)).alias("ms"))
        out = one if out is None else out.unionByName(one)
    return out


def relative_gain(curve: DataFrame, method: str, other: str) -> DataFrame:
    """(recall_gain, ms_ratio) of one method over another, each at its best recall: share by which recall rises, and times of time."""
    w = Window.partitionBy("method").orderBy(F.desc("recall"), "ms")
    best = curve.withColumn("r", F.row_number().over(w)).where("r = 1")
    a = best.where(F.col("method") == method).select(F.col("recall").alias("ra"), F.col("ms").alias("ma"))
    b = best.where(F.col("method") == other).select(F.col("recall").alias("rb"), F.col("ms").alias("mb"))
    return a.crossJoin(b).select((F.col("ra") / F.col("rb") - 1).alias("recall_gain"), (F.col("ma") / F.col("mb")).alias("ms_ratio"))  # one row each


def build_overhead(costs: DataFrame, base: str) -> DataFrame:
    """(method, seconds_ratio, dots_ratio) of builds (method, seconds, dots) over the build named ``base``."""
    b = costs.where(F.col("method") == base).select(F.col("seconds").alias("bs"), F.col("dots").alias("bd"))
    return costs.where(F.col("method") != base).crossJoin(b).select("method", (F.col("seconds") / F.col("bs")).alias("seconds_ratio"), (F.col("dots") / F.col("bd")).alias("dots_ratio"))


def expansion_gain(linked: DataFrame, plain: DataFrame) -> DataFrame:
    """(queries, linked, plain, gain) of two recall tables (qid, recall) over the same graph."""
    both = linked.select("qid", F.col("recall").alias("a")).join(plain.select("qid", F.col("recall").alias("b")), "qid")
    return both.agg(F.count("*").alias("queries"), F.avg("a").alias("linked"), F.avg("b").alias("plain"), (F.avg("a") - F.avg("b")).alias("gain"))


def error_distribution(approximate: DataFrame, exact: DataFrame) -> DataFrame:
    """(pairs, above, median, p90, p99, most): relative loss of approximate scores (qid, mv_id, score) against exact ones."""
    both = approximate.select("qid", "mv_id", F.col("score").alias("a")).join(exact.select("qid", "mv_id", F.col("score").alias("e")), ["qid", "mv_id"])
    loss = both.select(((F.col("e") - F.col("a")) / F.greatest(F.abs("e"), F.lit(1e-9))).alias("loss"))
    at = [F.percentile("loss", p).alias(name) for p, name in ((0.5, "median"), (0.9, "p90"), (0.99, "p99"))]
    return loss.agg(F.count("*").alias("pairs"), F.sum((F.col("loss") < -1e-9).cast("long")).alias("above"), *at, F.max("loss").alias("most"))


def size_correlation(pairs: DataFrame, *more) -> DataFrame:
    """(pairs, correlation, slope, low, high) of edge weights (weight, n) on object size, and ``more`` aggregates of the same pass."""
    return pairs.agg(
        F.count("*").alias("pairs"), F.corr("n", "weight").alias("correlation"), F.regr_slope("weight", "n").alias("slope"),
        F.min("weight").alias("low"), F.max("weight").alias("high"), *more,
    )


def counters(stats: DataFrame) -> DataFrame:
    """Means of the work counters of a search over its queries."""
    return stats.agg(F.count("*").alias("queries"), *(F.avg(c).alias(c) for c in ("scored", "hops", "pops", "dots", "lost")))


def describe(tokens: DataFrame, queries: DataFrame | None = None) -> DataFrame:
    """Objects, tokens, dimension and the distribution of tokens an object; with queries also their number."""
    per = tokens.groupBy("mv_id").agg(F.count("*").alias("c"), F.max(F.size("vec")).alias("d"))
    out = per.agg(
        F.count("*").alias("n_objects"), F.sum("c").alias("n_tokens"), F.max("d").alias("d"), F.min("c").alias("c_min"),
        F.percentile("c", 0.5).alias("c_median"), F.percentile("c", 0.9).alias("c_p90"), F.max("c").alias("c_max"),
    )
    if queries is None:
        return out
    return out.crossJoin(queries.agg(F.count_distinct("qid").alias("n_queries")))  # one row each


def relevance(results: DataFrame, relevant: DataFrame, k: int) -> DataFrame:
    """(queries, hit_rate, mrr, ndcg) of results (qid, rank, mv_id) against relevant pairs (qid, mv_id)."""
    rel = relevant.select("qid", "mv_id").distinct()
    hit = results.where(F.col("rank") <= k).join(rel, ["qid", "mv_id"])
    got = hit.groupBy("qid").agg(F.min("rank").alias("first"), F.sum(1 / F.log2(F.col("rank") + 1)).alias("dcg"))
    best = rel.groupBy("qid").agg(F.least(F.count("*"), F.lit(k)).alias("n"))
    best = best.withColumn("ideal", F.aggregate(F.sequence(F.lit(1), F.col("n").cast("int")), F.lit(0.0), lambda a, i: a + 1 / F.log2(i + 1)))
    each = best.join(got, "qid", "left")
    return each.agg(
        F.count("*").alias("queries"), F.avg(F.when(F.col("first").isNotNull(), 1.0).otherwise(0.0)).alias("hit_rate"),
        F.avg(F.coalesce(1 / F.col("first"), F.lit(0.0))).alias("mrr"), F.avg(F.coalesce(F.col("dcg") / F.col("ideal"), F.lit(0.0))).alias("ndcg"),
    )
