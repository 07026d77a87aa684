"""Search of a saved index as a table function of SQL."""

from __future__ import annotations

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..operators.similarity import QUERY_VALUES


def register(spark: SparkSession, name: str, path: str, scale: float = 1.0, limit: int = QUERY_VALUES) -> None:
    """``name``(tokens, k, ef): rank, mv_id and score of the best objects of the index at ``path``.

    Every worker holds the whole index, which is refused above ``limit`` values; search larger ones shard by shard.
    """
    from ..config import SearchConfig
    from ..operators import graph as G
    from ..operators import index as I

    ix = I.load(spark, path)
    n = ix.objects.agg(F.sum(F.size("vecs") * F.size(F.col("vecs")[0]))).first()[0] or 0
    if n > limit:
        raise ValueError(f"the index holds {n} values; search it shard by shard above {limit}")
    held = []
    for (shard,) in ix.graph.select("shard").distinct().orderBy("shard").collect():  # a row a shard
        t = ix.objects.where(F.col("shard") == shard)
        t = t.join(ix.links.select("mv_id", "links"), "mv_id", "left") if ix.links is not None else t.withColumn("links", F.lit(None).cast(G._LINKS))
        t = t.select("mv_id", "vecs", "links").toArrow()
        held.append((G.Shard.of(ix.cfg, t).restore(ix.graph.where(F.col("shard") == shard).toArrow()), t.column("mv_id").to_numpy(), t.column("links").combine_chunks()))
    everywhere = spark.sparkContext.broadcast(held)

    @F.udtf(returnType="rank int, mv_id long, score double")
    class Search:
        def __init__(self):
            self.shards = [(s, G.Lists(s, ids, links)) for s, ids, links in everywhere.value]

        def eval(self, tokens: list, k: int, ef: int):
            if not tokens:
                return
            q = np.array(tokens, float)
            cfg = SearchConfig(k=k, ef=ef, scale=scale)
            found = [(-v, int(s.ids[i])) for s, lists in self.shards for v, i in s.search(q, np.ones(len(q)), cfg, lists)]
            for rank, (v, i) in enumerate(sorted(found)[:k], 1):
                yield rank, i, -v

    spark.udtf.register(name, Search)
