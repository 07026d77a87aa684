"""Search over some shards only, and search of a whole batch by rounds of joins."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..config import IndexConfig, SearchConfig
from ..functions import kernel
from ..sources.shared import cut
from .graph import linked_nodes, nest_links, search_graph
from .shards import fit_centres, route_objects, rows_of  # noqa: F401
from .similarity import query_block, top_k

def search_routed(
    queries: DataFrame, routed: DataFrame, graph: DataFrame, centres: np.ndarray, cfg: SearchConfig, index: IndexConfig, links: DataFrame | None = None
) -> tuple[DataFrame, DataFrame]:
    """As ``search_graph``, but a query visits only the ``probe_shards`` shards of the centres nearest to its tokens."""
    p = cfg.probe_shards or len(centres)
    to = {qid: set(np.argsort(-(q @ centres.T).max(0) - (q @ centres.T).mean(0), kind="stable")[:p].tolist()) for qid, q, _ in query_block(queries)}
    return search_graph(queries, routed, graph, cfg, index, links, routes=to)


def score_candidates(queries: DataFrame, objs: DataFrame, pairs: DataFrame, gamma: int = 1) -> DataFrame:
    """(qid, mv_id, score) of candidate pairs (qid, mv_id): an object travels once, with the queries that ask for it."""
    return _scored(queries, objs, pairs, gamma).select("qid", "mv_id", "score")


def _scored(queries: DataFrame, objs: DataFrame, pairs: DataFrame, gamma: int, links: DataFrame | None = None, m: int = 0, scale: float = 1.0) -> DataFrame:
    """(qid, mv_id, score, linked): scores, and with ``links`` the m linked objects of highest priority of each pair."""
    block = {qid: (q, w) for qid, q, w in query_block(queries)}
    use = links is not None

    def run(batches):
        for b in batches:
            x, size = rows_of(b.column(1))
            start = np.cumsum(size) - size
            rows = []
            lists = b.column(3)
            for k, (mv, at, n, by) in enumerate(zip(b.column(0).to_pylist(), start.tolist(), size.tolist(), b.column(2).to_pylist())):
                own: dict = {}
                if use and lists[k].is_valid:
                    mine = lists[k].values
                    for t, to, key in zip(*(mine.field(c).to_pylist() for c in ("tok_ix", "linked_mv", "key"))):
                        own.setdefault(t, []).append((key, to))
                v = x[at : at + n]
                for qid in by:
                    q, w = block[qid]
                    to = linked_nodes(q, v, w, gamma, own, m, True, scale)[0] if own else []
                    rows.append((qid, mv, kernel.mv_sim(q, v, gamma, w), to))
            kinds = (pa.int64(), pa.int64(), pa.float64(), pa.list_(pa.int64()))
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds)], names=["qid", "mv_id", "score", "linked"])

    asked = pairs.groupBy("mv_id").agg(F.collect_list("qid").alias("by"))  # at most the query set, which is bounded
    met = asked.join(objs.select("mv_id", "vecs"), "mv_id")
    met = met.join(nest_links(links), "mv_id", "left") if use else met.withColumn("links", F.lit(None).cast("array<struct<tok_ix:int,linked_mv:bigint,key:double>>"))
    return met.select("mv_id", "vecs", "by", "links").mapInArrow(run, "qid long, mv_id long, score double, linked array<long>")


def search_rounds(
    queries: DataFrame, objs: DataFrame, edges: DataFrame, k: int, ef: int, starts: DataFrame, links: DataFrame | None = None, gamma: int = 1,
    m: int = 32, scale: float = 1.0, rounds: int = 100,
) -> DataFrame:
    """Top k of all queries together: every round each query's newly kept objects propose their neighbours.

    ``edges`` (src, dst) are joined, never held; with ``links`` (mv_id, tok_ix, pos, linked_mv, key) an object proposes besides the
    m linked objects of highest priority for the query, as in a shard's search. A query keeps its ef best, and
    the search ends when no query keeps anything new. With ef as large as the data it reaches all that the starts reach.
    """
    if ef < k:
        raise ValueError("ef must be at least k")
    step = cut(edges.select("src", "dst").distinct())
    lists = cut(nest_links(links)) if links is not None else None
    first = queries.select("qid").distinct().crossJoin(F.broadcast(starts.select("mv_id").distinct()))  # a few entries for each query
    kept = cut(_scored(queries, objs, first, gamma, lists, m, scale).withColumn("new", F.lit(True)))
    seen = kept.select("qid", "mv_id")
    best = Window.partitionBy("qid").orderBy(F.desc("score"), "mv_id")
    for _ in range(rounds):
        front = kept.where("new").select("qid", F.col("mv_id").alias("src"), "linked")
        found = front.join(step, "src").select("qid", F.col("dst").alias("mv_id"))
        found = found.unionByName(front.select("qid", F.explode("linked").alias("mv_id"))).distinct().join(seen, ["qid", "mv_id"], "left_anti")
        scored = cut(_scored(queries, objs, found, gamma, lists, m, scale).withColumn("new", F.lit(True)))
        seen = cut(seen.unionByName(scored.select("qid", "mv_id")))
        both = kept.withColumn("new", F.lit(False)).unionByName(scored)
        kept = cut(both.withColumn("r", F.row_number().over(best)).where(F.col("r") <= ef).drop("r"))
        if not kept.where("new").limit(1).count():
            break
    return top_k(kept.select("qid", "mv_id", "score"), k)
