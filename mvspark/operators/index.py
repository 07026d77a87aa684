"""An index as a whole: objects in shards, their graphs and links, on disk or not; built, searched, grown and checked."""

from __future__ import annotations

import json
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import IndexConfig, LinkConfig, SearchConfig
from . import graph as G
from . import links as L
from . import shards as P
from .similarity import QUERY_VALUES, query_block, top_k

PARTS = ("objects", "graph", "links", "centres")


@dataclass(frozen=True)
class Index:
    """``objects`` (shard, mv_id, n_tok, vecs), ``graph`` rows, ``links`` (shard, mv_id, links) or None, centres of the shards or None."""

    objects: DataFrame
    graph: DataFrame
    links: DataFrame | None
    centres: np.ndarray | None
    cfg: IndexConfig
    link_cfg: LinkConfig | None

    def search(self, queries: DataFrame, cfg: SearchConfig) -> tuple[DataFrame, DataFrame]:
        """(results, statistics). With ``probe_shards`` a query visits only the shards of the centres nearest to its tokens."""
        routes = None
        if cfg.probe_shards and self.centres is not None and len(self.centres):
            c = self.centres
            near = {qid: np.argsort(-((q @ c.T).max(0) + (q @ c.T).mean(0)), kind="stable") for qid, q, _ in query_block(queries)}
            routes = {qid: set(order[: cfg.probe_shards].tolist()) for qid, order in near.items()}
        return G.search_graph(queries, self.objects, self.graph, cfg, self.cfg, self.links, routes)

    def save(self, path: str) -> Index:
        """Write the parts, partitioned by shard, and the settings; returns the saved index. Links lie with their objects' shards."""
        spark = self.objects.sparkSession
        self.objects.write.partitionBy("shard").mode("overwrite").parquet(f"{path}/objects")
        self.graph.write.partitionBy("shard", "layer").mode("overwrite").parquet(f"{path}/graph")
        if self.links is not None:
            self.links.write.partitionBy("shard").mode("overwrite").parquet(f"{path}/links")
        c = self.centres if self.centres is not None else np.zeros((0, 0))
        spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(c)], "shard int, centre array<double>").coalesce(1).write.mode("overwrite").parquet(f"{path}/centres")
        told = json.dumps({"index": json.loads(self.cfg.to_json()), "links": json.loads(self.link_cfg.to_json()) if self.link_cfg else None, "routed": self.centres is not None})
        spark.createDataFrame([(told,)], "config string").coalesce(1).write.mode("overwrite").text(f"{path}/config")
        return load(spark, path)

    def append(self, objs: DataFrame) -> Index:
        """With new objects: each goes to its shard, is inserted there, and the shard's links are made anew."""
        new = P.route_objects(objs, self.centres) if self.centres is not None else P.with_shards(objs.select("mv_id", "n_tok", "vecs"), self.cfg.n_shards)
        new = new.select("shard", "mv_id", "n_tok", "vecs")
        graph = G.append(self.graph, self.objects, new, self.cfg)
        every = self.objects.select("shard", "mv_id", "n_tok", "vecs").unionByName(new)
        links = None
        if self.links is not None:
            touched = new.select("shard").distinct()
            made = nested(L.shard_links(every.join(F.broadcast(touched), "shard"), self.link_cfg))  # a row a shard
            links = self.links.join(F.broadcast(touched), "shard", "left_anti").select("shard", "mv_id", "links").unionByName(made)
        return replace(self, objects=every, graph=graph, links=links)

    def delete(self, ids: DataFrame) -> Index:
        """Without the objects of ``ids`` (mv_id); nodes that lose neighbours look for new ones. Links to them lead nowhere and are skipped."""
        gone = ids.select("mv_id").distinct()
        graph = G.delete_relinked(self.graph, self.objects, gone, self.cfg)
        links = self.links.join(gone, "mv_id", "left_anti") if self.links is not None else None
        return replace(self, objects=self.objects.join(gone, "mv_id", "left_anti"), graph=graph, links=links)

    def validate(self) -> DataFrame:
        """(rule, violations) of graph and links: as ``check_graph``, and links that leave their shard or rise."""
        out = G.check_graph(self.graph, self.cfg.M)
        if self.links is not None:
            flat = self.links.select("mv_id", F.posexplode("links").alias("i", "l")).select("mv_id", F.col("l.tok_ix").alias("tok_ix"), F.col("i").alias("pos"), F.col("l.linked_mv").alias("linked_mv"), F.col("l.key").alias("key"))
            lost = L.link_loss(flat, self.objects).select(F.lit("link_shard").alias("rule"), F.col("lost").alias("violations"))
            rise = L.unsorted_links(flat).agg(F.count("*").alias("violations")).select(F.lit("link_order").alias("rule"), "violations")
            out = out.unionByName(lost).unionByName(rise)
        return out


def nested(links: DataFrame) -> DataFrame:
    return G.nest_links(links).join(links.select("mv_id", "shard").distinct(), "mv_id").select("shard", "mv_id", "links")


def build_index(objs: DataFrame, cfg: IndexConfig, link_cfg: LinkConfig | None = None, shard_bytes: int | None = None) -> Index:
    """Shards (as many as ``n_shards``, or as keep each below ``shard_bytes``), a graph and links in each."""
    if shard_bytes:
        cfg = replace(cfg, n_shards=P.n_shards(objs, shard_bytes))
    centres = P.fit_centres(objs, cfg.n_shards) if cfg.shard_by == "centroid" else None
    placed = P.route_objects(objs, centres) if centres is not None else P.with_shards(objs.select("mv_id", "n_tok", "vecs"), cfg.n_shards)
    placed = placed.select("shard", "mv_id", "n_tok", "vecs")
    graph = G.build_graph(placed, cfg)
    links = nested(L.shard_links(placed, link_cfg)) if link_cfg is not None else None
    return Index(placed, graph, links, centres, cfg, link_cfg)


def load(spark: SparkSession, path: str) -> Index:
    told = json.loads(spark.read.text(f"{path}/config").first()[0])
    centres = None
    if told["routed"]:
        rows = spark.read.parquet(f"{path}/centres").orderBy("shard").collect()  # one a shard
        centres = np.array([r.centre for r in rows]) if rows else np.zeros((0, 0))
    links = spark.read.parquet(f"{path}/links").select("shard", "mv_id", "links") if told["links"] else None
    objects = spark.read.parquet(f"{path}/objects").select("shard", "mv_id", "n_tok", "vecs")
    graph = spark.read.parquet(f"{path}/graph").select(*G._GRAPH.names)
    return Index(objects, graph, links, centres, IndexConfig(**told["index"]), LinkConfig(**told["links"]) if told["links"] else None)


def size_of(spark: SparkSession, path: str) -> dict[str, int]:
    """Bytes of the files of each part of a saved index."""
    jvm = spark.sparkContext._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    fs = at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    out = {}
    for part in PARTS:
        p = jvm.org.apache.hadoop.fs.Path(f"{path}/{part}")
        out[part] = int(fs.getContentSummary(p).getLength()) if fs.exists(p) else 0
    return out


def search_everywhere(queries: DataFrame, index: Index, cfg: SearchConfig, limit: int = QUERY_VALUES) -> DataFrame:
    """Results of many queries against a small index that every worker holds whole; a larger index is refused."""
    n = index.objects.agg(F.sum(F.size("vecs") * F.size(F.col("vecs")[0]))).first()[0] or 0
    if n > limit:
        raise ValueError(f"the index holds {n} values; search it shard by shard above {limit}")
    held = []
    for (shard,) in index.graph.select("shard").distinct().orderBy("shard").collect():
        t = index.objects.where(F.col("shard") == shard)
        t = t.join(index.links.select("mv_id", "links"), "mv_id", "left") if index.links is not None and cfg.linked else t.withColumn("links", F.lit(None).cast(G._LINKS))
        t = t.select("mv_id", "vecs", "links").toArrow()
        s = G.Shard.of(index.cfg, t).restore(index.graph.where(F.col("shard") == shard).toArrow())
        held.append((s, t.column("links").combine_chunks() if index.links is not None and cfg.linked else None, t.column("mv_id").to_numpy()))
    spark = queries.sparkSession
    everywhere = spark.sparkContext.broadcast(held)
    asked = queries.groupBy("qid").agg(F.array_sort(F.collect_list(F.struct("q_ix", "vec", *(["weight"] if "weight" in queries.columns else [F.lit(1.0).alias("weight")])))).alias("t"))
    asked = asked.select("qid", F.col("t.vec").alias("vecs"), F.col("t.weight").alias("w"))

    def run(batches):
        shards = [(s, G.Lists(s, ids, column) if column is not None else None) for s, column, ids in everywhere.value]
        for b in batches:
            x, size = P.rows_of(b.column(1))
            start = np.cumsum(size) - size
            rows = []
            for qid, at, n, w in zip(b.column(0).to_pylist(), start.tolist(), size.tolist(), b.column(2).to_pylist()):
                for s, lists in shards:
                    rows += [(qid, int(s.ids[i]), v) for v, i in s.search(x[at : at + n].astype(np.float64), np.array(w, float), cfg, lists)]
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate((pa.int64(), pa.int64(), pa.float64()))], names=["qid", "mv_id", "score"])

    return top_k(asked.mapInArrow(run, "qid long, mv_id long, score double"), cfg.k)
