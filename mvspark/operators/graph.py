"""The layered graph over whole objects: layers, sequential and bulk builds, search with and without links.

A shard is built and searched by one worker, in memory; shards are independent, so a build is one shuffle
by shard and a search reads the shards' tables and the queries. Layers come from hashed ids, so a lost
task builds the same graph again. All new nodes of a step are scored by one matrix product.
"""

from __future__ import annotations

import hashlib
import heapq
import math
import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..config import IndexConfig, SearchConfig
from ..functions import kernel
from ..sources.shared import cut
from .shards import rows_of, single, with_shards
from .similarity import every_pair, pairs_in_cells, query_block, score_pairs, top_k

GRAPH = "shard int, layer int, mv_id long, top_layer int, nbrs array<long>, weights array<double>, entry boolean"
_GRAPH = pa.schema([
    ("shard", pa.int32()), ("layer", pa.int32()), ("mv_id", pa.int64()), ("top_layer", pa.int32()),
    ("nbrs", pa.list_(pa.int64())), ("weights", pa.list_(pa.float64())), ("entry", pa.bool_()),
])


def assign_layers(ids: DataFrame, cfg: IndexConfig) -> DataFrame:
    """(mv_id, top_layer): floor of minus the log of a hashed uniform times the level scale."""
    hexed = F.substring(F.md5(F.concat(F.lit(f"{cfg.seed}:"), F.col("mv_id").cast("string"))), 1, 8)
    u = (F.conv(hexed, 16, 10).cast("double") + 0.5) / F.lit(4294967296.0)
    return ids.select("mv_id", F.floor(-F.log(u) * F.lit(cfg.level_scale)).cast("int").alias("top_layer"))


def layer_members(layers: DataFrame) -> DataFrame:
    return layers.select("mv_id", F.explode(F.sequence(F.lit(0), F.col("top_layer"))).alias("layer"))


def entry_point(layers: DataFrame) -> DataFrame:
    return layers.orderBy(F.desc("top_layer"), "mv_id").limit(1)


def levels(n: int, cfg: IndexConfig) -> dict[int, int]:
    """Layers of the ids 0..n-1, drawn as ``assign_layers`` draws them."""
    out = {}
    for i in range(n):
        u = (int(hashlib.md5(f"{cfg.seed}:{i}".encode()).hexdigest()[:8], 16) + 0.5) / 4294967296.0
        out[i] = int(-math.log(u) * cfg.level_scale)
    return out


class Shard:
    """One graph in memory. Nodes are places in ``ids``, which rise, so that ties by place are ties by id."""

    def __init__(self, cfg: IndexConfig, ids: np.ndarray, x: np.ndarray, size: np.ndarray):
        order = np.argsort(ids, kind="stable")
        start = np.cumsum(size) - size
        self.cfg, self.ids = cfg, np.asarray(ids, np.int64)[order]
        self.block = kernel.Block(x[kernel.spans(start[order], np.asarray(size)[order])].astype(np.float32, copy=False), np.asarray(size)[order])
        self.top = np.full(len(self.ids), -1, np.int64)
        self.near: list[dict[int, list[tuple[float, int]]]] = []
        self.entry: int | None = None
        self.work = {"scored": 0, "hops": 0, "pops": 0}

    @classmethod
    def of(cls, cfg: IndexConfig, table: pa.Table) -> Shard:
        x, size = rows_of(table.column("vecs"))
        return cls(cfg, table.column("mv_id").to_numpy(), x, size)

    def place(self, ids) -> np.ndarray:
        """Places of ids, -1 where absent."""
        ids = np.asarray(ids, np.int64)
        at = np.minimum(np.searchsorted(self.ids, ids), len(self.ids) - 1) if len(self.ids) else np.zeros(len(ids), np.int64)
        return np.where(self.ids[at] == ids, at, -1) if len(self.ids) else at - 1

    def restore(self, graph: pa.Table) -> Shard:
        """Take up the graph's rows; nodes without an object here are left out."""
        g = {c: graph.column(c).to_pylist() for c in ("layer", "top_layer", "nbrs", "weights", "entry")}
        at = self.place(graph.column("mv_id").to_numpy())
        self.near = [{} for _ in range(max(g["layer"], default=-1) + 1)]
        for k, i in enumerate(at.tolist()):
            if i < 0:
                continue
            ends = self.place(g["nbrs"][k]).tolist() if g["nbrs"][k] else []
            self.near[g["layer"][k]][i] = [(w, e) for w, e in zip(g["weights"][k], ends) if e >= 0]
            self.top[i] = g["top_layer"][k]
            if g["entry"][k]:
                self.entry = i
        return self

    def table(self, shard: int) -> pa.Table:
        """The graph as rows."""
        cols: list[list] = [[] for _ in _GRAPH]
        for layer, nodes in enumerate(self.near):
            for i, edges in nodes.items():
                row = (shard, layer, int(self.ids[i]), int(self.top[i]), self.ids[[e for _, e in edges]].tolist() if edges else [], [w for w, _ in edges], i == self.entry)
                for c, v in zip(cols, row):
                    c.append(v)
        return pa.Table.from_arrays([pa.array(c, f.type) for c, f in zip(cols, _GRAPH)], schema=_GRAPH)

    def edges(self, i: int, some: list[int]) -> list[float]:
        self.work["scored"] += len(some)
        c = self.cfg
        return self.block.edges(i, some, c.gamma, c.edge_fn, c.edge_sim == "clustered", c.beta).tolist()

    def search_layer(self, score, layer: int, starts: list[int], ef: int, expand=None, known: dict | None = None, fill: bool = False) -> list[tuple[float, int]]:
        """Best-first search with a bounded answer list; ``expand`` proposes nodes besides the neighbours.

        A walk that ends with room in the list (``fill``) goes on from the nodes that no edge led to, so that a list as wide as the layer holds all of it.
        """
        known = {} if known is None else known
        nodes = self.near[layer]

        def values(some: list[int]) -> list[float]:
            new = [n for n in some if n not in known]
            if new:
                known.update(zip(new, score(new)))
            return [known[n] for n in some]

        first = sorted(set(starts))
        seen = set(first)
        got = values(first)
        open_ = [(-v, n) for v, n in zip(got, first)]
        best = [(v, -n) for v, n in zip(got, first)]
        heapq.heapify(open_)
        heapq.heapify(best)
        while len(best) > ef:
            heapq.heappop(best)
        strands = iter(list(nodes) if fill else ())
        while open_ or (fill and len(best) < ef and len(seen) < len(nodes)):
            if not open_:
                strand = next(x for x in strands if x not in seen)
                seen.add(strand)
                v = values([strand])[0]
                open_.append((-v, strand))
                heapq.heappush(best, (v, -strand))
            s, n = heapq.heappop(open_)
            if len(best) >= ef and -s < best[0][0]:
                break
            self.work["hops"] += 1
            new = [x for _, x in nodes.get(n, ())]
            if expand:
                new += expand(n)
            fresh = []
            for x in new:
                if x not in seen and x in nodes:
                    seen.add(x)
                    fresh.append(x)
            for x, v in zip(fresh, values(fresh)):
                if len(best) < ef or v > best[0][0]:
                    heapq.heappush(open_, (-v, x))
                    heapq.heappush(best, (v, -x))
                    if len(best) > ef:
                        heapq.heappop(best)
        return sorted(((v, -n) for v, n in best), key=lambda t: (-t[0], t[1]))

    def choose(self, found: list[tuple[float, int]]) -> list[tuple[float, int]]:
        """The M nearest, or first those nearer to the new node than to a chosen one and then the nearest of the rest."""
        m = self.cfg.M
        if self.cfg.select == "nearest" or len(found) <= m:
            return found[:m]
        kept: list[tuple[float, int]] = []
        for w, n in found:
            if len(kept) < m and all(e < w for e in (self.edges(n, [o for _, o in kept]) if kept else ())):
                kept.append((w, n))
        rest = [e for e in found if e not in kept]
        return sorted(kept + rest[: m - len(kept)], key=lambda t: (-t[0], t[1]))

    def insert(self, node: int, layer: int) -> None:
        cfg = self.cfg
        self.top[node] = layer
        while len(self.near) <= layer:
            self.near.append({})
        if self.entry is not None:
            starts, known = [self.entry], {}
            score = lambda some: self.edges(node, some)
            high = int(self.top[self.entry])
            for at in range(high, layer, -1):
                starts = [self.search_layer(score, at, starts, 1, known=known)[0][1]]
            for at in range(min(layer, high), -1, -1):
                found = self.search_layer(score, at, starts, cfg.ef_construction, known=known)
                mine = self.choose(found)
                self.near[at][node] = mine
                for w, n in mine:
                    full = sorted([*self.near[at][n], (w, node)], key=lambda t: (-t[0], t[1]))
                    for _, gone in full[cfg.M :]:
                        if cfg.trim == "mirror":
                            self.near[at][gone] = [e for e in self.near[at][gone] if e[1] != n]
                    self.near[at][n] = full[: cfg.M]
                starts = [n for _, n in found] if cfg.descend == "all" else [found[0][1]]
        for at in range(layer + 1):
            self.near[at].setdefault(node, [])
        if self.entry is None or layer > self.top[self.entry]:
            self.entry = node

    def insert_all(self, layers: dict[int, int]) -> Shard:
        """Insert the objects of ``layers`` (id to layer) in order of ids."""
        for i in sorted(layers):
            self.insert(int(self.place([i])[0]), layers[i])
        return self

    def nearest(self, q: np.ndarray, ef: int) -> list[tuple[float, int]]:
        """The ef nearest nodes of one vector, for graphs of single tokens."""
        q = np.asarray(q, np.float32)[None]
        score, known, starts = lambda some: self.block.scores(q, some).tolist(), {}, [self.entry]
        for at in range(int(self.top[self.entry]), 0, -1):
            starts = [self.search_layer(score, at, starts, 1, known=known)[0][1]]
        return self.search_layer(score, 0, starts, ef, known=known)

    def search(self, q: np.ndarray, w: np.ndarray, cfg: SearchConfig, links: Lists | None = None) -> list[tuple[float, int]]:
        """The top k as (score, place): greedy descent, then the base layer with link expansion if asked.

        With ``final`` exact the whole answer list is scored again exactly, in double precision.
        """
        if self.entry is None:
            return []
        known: dict[int, float] = {}
        q4, block = q.astype(np.float32), self.block
        if cfg.mode == "clustered":
            groups = kernel.cluster_tokens(q)
            score = lambda some: block.clustered_scores(q4, groups, some, cfg.gamma, w, cfg.beta).tolist()
        else:
            score = lambda some: block.scores(q4, some, cfg.gamma, w).tolist()

        def expand(n: int) -> list[int]:
            v = block.of(n)
            block.dots += len(q) * len(v)
            out, pops = best_linked(q, v, w, cfg.gamma, links.of(n), self.cfg.M, cfg.distinct_pops, cfg.scale)
            self.work["pops"] += pops
            return out

        use = expand if cfg.linked and links is not None else None
        starts = [self.entry]
        for at in range(int(self.top[self.entry]), 0, -1):
            starts = [self.search_layer(score, at, starts, 1, use if cfg.expand_layers == "all" else None, known)[0][1]]
        found = self.search_layer(score, 0, starts, max(cfg.width, cfg.k), use, known, fill=True)
        self.work["scored"] += len(known)
        if cfg.final == "exact" or cfg.mode == "exact":
            some = [n for _, n in found]
            before = block.dots
            exact = kernel.Block(block.x[kernel.spans(block.start[some], block.size[some])].astype(np.float64), block.size[some])
            found = sorted(zip(exact.scores(q, np.arange(len(some)), cfg.gamma, w).tolist(), some), key=lambda t: (-t[0], t[1]))
            block.dots = before + (exact.dots if cfg.mode == "clustered" else 0)  # the same products as in the walk, if that was exact
        return found[: cfg.k]


class Lists:
    """Link lists of a shard's nodes: for each token the linked nodes of falling key."""

    def __init__(self, shard: Shard, ids, column):
        self.shard, self.rows = shard, dict(zip(shard.place(ids).tolist(), range(len(ids))))
        self.column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
        self.lost = 0
        self.ready: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]] = {}

    def of(self, node: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(token, linked node, key) of all links of a node that stay in the shard, by token and place."""
        if node not in self.ready:
            none = np.zeros(0, np.int64)
            tok, at, key = none, none, np.zeros(0)
            k = self.rows.get(node)
            mine = self.column[k].values if k is not None and self.column[k].is_valid else None
            if mine is not None and len(mine):
                tok, linked, key = (mine.field(c).to_numpy() for c in ("tok_ix", "linked_mv", "key"))
                at = self.shard.place(linked)
                self.lost += int((at < 0).sum())  # a linked object of another shard
                tok, at, key = tok[at >= 0], at[at >= 0], key[at >= 0]
            self.ready[node] = tok, at, key
        return self.ready[node]


def best_linked(q, vecs, w, gamma: int, links: tuple, m: int, distinct: bool = True, scale: float = 1.0) -> tuple[list[int], int]:
    """(the m linked objects of highest priority, links looked at): all priorities at once, in the order that pops would take them.

    ``scale`` is the squared length of token vectors: relevance is the softmax over unit vectors' contributions.
    """
    tok, node, key = links
    if not len(tok):
        return [], 0
    priority = kernel.softmax(kernel.contribution(q, vecs, gamma, w) / scale)[tok] * key
    order = node[np.lexsort((node, -priority))].tolist()
    if not distinct:
        return list(dict.fromkeys(order[:m])), min(m, len(order))
    out: dict[int, None] = {}
    for pops, n in enumerate(order, 1):
        out[n] = None
        if len(out) == m:
            return list(out), pops
    return list(out), len(order)


def linked_nodes(q, vecs, w, gamma: int, lists: dict[int, list[tuple[float, int]]], m: int, distinct: bool = True, scale: float = 1.0) -> tuple[list[int], int]:
    """As ``best_linked``, lazily: pops from a heap of the heads of the tokens' sorted lists (key, node)."""
    return popped(kernel.softmax(kernel.contribution(q, vecs, gamma, w) / scale), lists, m, distinct)


def popped(rel, lists: dict[int, list[tuple[float, int]]], m: int, distinct: bool = True) -> tuple[list[int], int]:
    """The pops of ``linked_nodes``, from the relevance of each token."""
    heap = [(-rel[t] * l[0][0], l[0][1], t, 0) for t, l in lists.items() if l]
    heapq.heapify(heap)
    out: list[int] = []
    pops = 0
    while heap and (len(out) < m if distinct else pops < m):
        _, n, t, i = heap[0]
        pops += 1
        if n not in out:
            out.append(n)
        if i + 1 < len(lists[t]):
            key, nxt = lists[t][i + 1]
            heapq.heapreplace(heap, (-rel[t] * key, nxt, t, i + 1))
        else:
            heapq.heappop(heap)
    return out, pops


def build_graph(objs: DataFrame, cfg: IndexConfig) -> DataFrame:
    """(shard, layer, mv_id, top_layer, nbrs, weights, entry): one worker a shard inserts its objects in id order."""
    rows = with_shards(objs.join(assign_layers(objs, cfg), "mv_id"), cfg.n_shards).select("shard", "mv_id", "top_layer", single())

    def build(t: pa.Table) -> pa.Table:
        layers = dict(zip(t.column("mv_id").to_pylist(), t.column("top_layer").to_pylist()))
        return Shard.of(cfg, t).insert_all(layers).table(t.column("shard")[0].as_py())

    return rows.groupBy("shard").applyInArrow(build, GRAPH)


def build_work(objs: DataFrame, cfg: IndexConfig) -> DataFrame:
    """(shard, objects, tokens, scored, dots, seconds) of building the shards' graphs; the graphs are not kept."""
    rows = with_shards(objs.join(assign_layers(objs, cfg), "mv_id"), cfg.n_shards).select("shard", "mv_id", "top_layer", single())

    def build(t: pa.Table) -> pa.Table:
        layers = dict(zip(t.column("mv_id").to_pylist(), t.column("top_layer").to_pylist()))
        begin = time.perf_counter()
        s = Shard.of(cfg, t).insert_all(layers)
        out = {"shard": [t.column("shard")[0].as_py()], "objects": [len(s.ids)], "tokens": [int(s.block.size.sum())],
               "scored": [s.work["scored"]], "dots": [s.block.dots], "seconds": [time.perf_counter() - begin]}
        return pa.table(out).cast(pa.schema([("shard", pa.int32()), ("objects", pa.int64()), ("tokens", pa.int64()), ("scored", pa.int64()), ("dots", pa.int64()), ("seconds", pa.float64())]))

    return rows.groupBy("shard").applyInArrow(build, "shard int, objects long, tokens long, scored long, dots long, seconds double")


def bulk_graph(objs: DataFrame, m: int, cells: DataFrame | None = None, gamma: int = 1, rounds: int = 0, mirror: bool = False) -> DataFrame:
    """(src, dst, weight): the m nearest objects under the edge weight among those sharing a cell, then by rounds of joins.

    Without ``cells`` every object meets every other, a source at a time. A round lets each object meet the neighbours of
    its neighbours. ``mirror`` adds the other direction of every edge before the m best are kept.
    """
    w = Window.partitionBy("src").orderBy(F.desc("weight"), "dst")

    def best(edges: DataFrame) -> DataFrame:
        if mirror:
            edges = edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight")).distinct()
        return edges.withColumn("r", F.row_number().over(w)).where(F.col("r") <= m).drop("r")

    if cells is None:
        kept = best(every_pair(objs, objs, gamma=gamma, keep=None if mirror else m, skip_own=True))
    else:
        kept = best(pairs_in_cells(objs, cells, gamma, None if mirror else m))
    for _ in range(rounds):
        kept = cut(kept)
        step = kept.select(F.col("src").alias("dst0"), F.col("dst").alias("dst1"))
        far = kept.join(step, kept["dst"] == step["dst0"]).select("src", F.col("dst1").alias("dst")).where("src <> dst").distinct()
        far = far.join(kept.select("src", "dst"), ["src", "dst"], "left_anti")
        kept = best(kept.unionByName(score_pairs(objs, objs, far, gamma=gamma)))
    return kept


#: queries for which a task takes a graph of its own
QUERIES = 32
_LINKS = "array<struct<tok_ix:int,linked_mv:bigint,key:double>>"


def nest_links(links: DataFrame) -> DataFrame:
    """(mv_id, links): every object's lists in one row, by token and place."""
    if "links" in links.columns:
        return links.select("mv_id", "links")
    own = links.groupBy("mv_id").agg(F.array_sort(F.collect_list(F.struct("tok_ix", "pos", "linked_mv", "key"))).alias("l"))
    flat = F.transform("l", lambda x: F.struct(x["tok_ix"].cast("int").alias("tok_ix"), x["linked_mv"].alias("linked_mv"), x["key"].alias("key")))
    return own.select("mv_id", flat.cast(_LINKS).alias("links"))


STATS = "scored long, hops long, pops long, dots long, lost long, ms double"


def search_graph(queries: DataFrame, objs: DataFrame, graph: DataFrame, cfg: SearchConfig, index: IndexConfig, links: DataFrame | None = None, routes: dict | None = None) -> tuple[DataFrame, DataFrame]:
    """(results, statistics): every shard, or those that ``routes`` names for a query, answers; k rows each are merged.

    Large query sets are cut into as many runs as the cluster has cores, each with the shard's graph to itself, as walks of
    different queries share nothing. Statistics sum over the shards a query visited: objects scored, nodes left, link entries popped, token products, links that
    pointed to other shards, milliseconds.
    """
    block = query_block(queries)
    nodes = with_shards(objs, index.n_shards).select("shard", "mv_id", single())
    use = cfg.linked and links is not None
    if use:
        nodes = nodes.join(nest_links(links), "mv_id", "left")
    else:
        nodes = nodes.withColumn("links", F.lit(None).cast(_LINKS))
    if routes is not None:
        asked = sorted({s for some in routes.values() for s in some})
        nodes, graph = nodes.where(F.col("shard").isin(asked)), graph.where(F.col("shard").isin(asked))
    runs = max(1, min(objs.sparkSession.sparkContext.defaultParallelism, len(block) // QUERIES))
    every_run = F.explode(F.sequence(F.lit(0), F.lit(runs - 1)))

    def answer(n: pa.Table, g: pa.Table) -> pa.Table:
        cols: dict[str, list] = {c: [] for c in ("shard", "qid", "mv_id", "score", "scored", "hops", "pops", "dots", "lost", "ms")}
        if len(n) and len(g):
            own, run = n.column("shard")[0].as_py(), n.column("run")[0].as_py()
            n, g = n.drop_columns("run"), g.drop_columns("run")
            s = Shard.of(index, n).restore(g)
            lists = Lists(s, n.column("mv_id").to_numpy(), n.column("links")) if use else None
            for qid, q, w in block[run::runs]:
                if routes is not None and own not in routes.get(qid, ()):
                    continue
                s.work, s.block.dots, begin = dict.fromkeys(s.work, 0), 0, time.perf_counter()
                lost = lists.lost if lists else 0
                found = s.search(q, w, cfg, lists)
                ms = (time.perf_counter() - begin) * 1000
                more = (s.work["scored"], s.work["hops"], s.work["pops"], s.block.dots, (lists.lost - lost) if lists else 0, ms)
                for v, i in found:
                    for c, x in zip(cols.values(), (own, qid, int(s.ids[i]), v, *more)):
                        c.append(x)
        kinds = [pa.int32(), pa.int64(), pa.int64(), pa.float64(), *[pa.int64()] * 5, pa.float64()]
        return pa.Table.from_arrays([pa.array(c, t) for c, t in zip(cols.values(), kinds)], names=list(cols))

    sides = [d.withColumn("run", every_run).groupBy("shard", "run") for d in (nodes, graph)]
    got = sides[0].cogroup(sides[1]).applyInArrow(answer, f"shard int, qid long, mv_id long, score double, {STATS}")
    work = ("scored", "hops", "pops", "dots", "lost", "ms")
    stats = got.groupBy("qid", "shard").agg(*(F.max(c).alias(c) for c in work)).groupBy("qid").agg(*(F.sum(c).alias(c) for c in work))
    return top_k(got, cfg.k), stats


def check_graph(graph: DataFrame, m: int) -> DataFrame:
    """(rule, violations): degree, nesting, entries, endpoints, self loops."""
    edges = graph.select("shard", "layer", F.col("mv_id").alias("src"), F.explode("nbrs").alias("dst"))
    at = graph.select("shard", "layer", F.col("mv_id").alias("dst"))
    below = graph.select("shard", (F.col("layer") + 1).alias("layer"), "mv_id")
    top = graph.groupBy("shard").agg(F.max("top_layer").alias("high"))
    ends = graph.where("entry").select("shard", "mv_id", "top_layer").distinct().join(top, "shard")
    parts = {
        "degree": graph.where(F.size("nbrs") > m), "self": edges.where("src = dst"),
        "nesting": graph.where("layer > 0").join(below, ["shard", "layer", "mv_id"], "left_anti"),
        "endpoint": edges.join(at, ["shard", "layer", "dst"], "left_anti"), "entry": ends.where("top_layer < high"),
    }
    out = None
    for rule, bad in parts.items():
        one = bad.agg(F.count("*").alias("violations")).select(F.lit(rule).alias("rule"), "violations")
        out = one if out is None else out.unionByName(one)
    return out


def reachable(graph: DataFrame, rounds: int = 200) -> DataFrame:
    """(shard, nodes, reached, mirrored): nodes of the base layer, those its edges reach from the entry, and the share of edges with a mirror.

    Every round joins the newly reached nodes with their edges; the driver reads one number a round.
    """
    base = graph.where("layer = 0")
    edges = cut(base.select("shard", F.col("mv_id").alias("src"), F.explode("nbrs").alias("dst")))
    seen = cut(base.where("entry").select("shard", "mv_id").distinct())
    front = seen
    for _ in range(rounds):
        step = front.withColumnRenamed("mv_id", "src").join(edges, ["shard", "src"]).select("shard", F.col("dst").alias("mv_id"))
        front = cut(step.distinct().join(seen, ["shard", "mv_id"], "left_anti"))
        if not front.limit(1).count():
            break
        seen = cut(seen.unionByName(front))
    else:
        raise RuntimeError(f"the graph is not walked through in {rounds} rounds")
    back = edges.select("shard", F.col("dst").alias("src"), F.col("src").alias("dst"), F.lit(1).alias("hit"))
    mirrored = edges.join(back, ["shard", "src", "dst"], "left").groupBy("shard").agg(F.avg(F.coalesce("hit", F.lit(0))).alias("mirrored"))
    out = base.groupBy("shard").agg(F.count("*").alias("nodes")).join(seen.groupBy("shard").agg(F.count("*").alias("reached")), "shard", "left")
    return out.join(mirrored, "shard", "left").select("shard", "nodes", F.coalesce("reached", F.lit(0)).alias("reached"), "mirrored")


def hub_report(graph: DataFrame, objs: DataFrame | None = None) -> DataFrame:
    """In-degrees of the base layer; with objects, percentiles of in-degree by object size."""
    edges = graph.where("layer = 0").select(F.explode("nbrs").alias("mv_id"))
    degree = edges.groupBy("mv_id").agg(F.count("*").alias("in_degree"))
    if objs is None:
        return degree
    each = objs.select("mv_id", "n_tok").join(degree, "mv_id", "left").select("n_tok", F.coalesce("in_degree", F.lit(0)).alias("d"))
    at = [F.percentile("d", q).alias(name) for q, name in ((0.5, "median"), (0.9, "p90"), (0.99, "p99"), (1.0, "most"))]
    return each.groupBy("n_tok").agg(F.count("*").alias("objects"), F.sum("d").alias("edges"), *at)


def append(graph: DataFrame, objs: DataFrame, new: DataFrame, cfg: IndexConfig) -> DataFrame:
    """The graph with new objects inserted, shard by shard; appending in id order equals building at once."""
    mark = lambda df, x: df.select("mv_id", "vecs", F.lit(x).alias("new"), *(["shard"] if "shard" in df.columns else []))
    every = mark(objs, False).unionByName(mark(new, True))
    rows = with_shards(every.join(assign_layers(every, cfg), "mv_id"), cfg.n_shards).select("shard", "mv_id", "vecs", "new", "top_layer")

    def grow(n: pa.Table, g: pa.Table) -> pa.Table:
        if not len(n):
            return g.select(_GRAPH.names).cast(_GRAPH)
        s = Shard.of(cfg, n).restore(g)
        layers = {i: t for i, t, x in zip(*(n.column(c).to_pylist() for c in ("mv_id", "top_layer", "new"))) if x}
        return s.insert_all(layers).table(n.column("shard")[0].as_py())

    return rows.groupBy("shard").cogroup(graph.groupBy("shard")).applyInArrow(grow, GRAPH)


def delete(graph: DataFrame, gone: DataFrame) -> DataFrame:
    """The graph without the objects of ``gone`` (mv_id); a shard's entry moves to its highest node left."""
    left = graph.join(gone.select("mv_id").distinct(), "mv_id", "left_anti")
    edges = left.select("shard", "layer", "mv_id", F.posexplode(F.arrays_zip("nbrs", "weights")).alias("at", "e"))
    edges = edges.join(gone.select(F.col("mv_id").alias("g")).distinct(), F.col("e.nbrs") == F.col("g"), "left_anti")
    kept = edges.groupBy("shard", "layer", "mv_id").agg(F.array_sort(F.collect_list(F.struct("at", "e"))).alias("l"))
    top = left.groupBy("shard").agg(F.min_by("mv_id", F.struct(-F.col("top_layer"), F.col("mv_id"))).alias("first"))
    out = left.select("shard", "layer", "mv_id", "top_layer").join(kept, ["shard", "layer", "mv_id"], "left").join(top, "shard")
    none = F.array().cast("array<bigint>"), F.array().cast("array<double>")
    return out.select(
        "shard", "layer", "mv_id", "top_layer", F.coalesce(F.col("l.e.nbrs"), none[0]).alias("nbrs"),
        F.coalesce(F.col("l.e.weights"), none[1]).alias("weights"), (F.col("mv_id") == F.col("first")).alias("entry"),
    )


def delete_relinked(graph: DataFrame, objs: DataFrame, gone: DataFrame, cfg: IndexConfig) -> DataFrame:
    """As ``delete``, and every node that lost neighbours looks for new ones among those that its lost ones had."""
    rows = with_shards(objs, cfg.n_shards).join(gone.select("mv_id", F.lit(True).alias("gone")).distinct(), "mv_id", "left")
    rows = rows.select("shard", "mv_id", "vecs", F.coalesce("gone", F.lit(False)).alias("gone"))

    def mend(n: pa.Table, g: pa.Table) -> pa.Table:
        if not len(n) or not len(g):
            return _GRAPH.empty_table()
        s = Shard.of(cfg, n).restore(g)
        lost = set(s.place([i for i, x in zip(n.column("mv_id").to_pylist(), n.column("gone").to_pylist()) if x]).tolist())
        first = min((i for i in np.flatnonzero(s.top >= 0).tolist() if i not in lost), key=lambda i: (-s.top[i], i), default=None)
        new: list[dict] = []
        for layer in s.near:
            out = {}
            for i, e in layer.items():
                if i in lost:
                    continue
                if any(x in lost for _, x in e):
                    far = {y for _, x in e if x in lost for _, y in layer.get(x, [])}
                    some = sorted(far - {x for _, x in e} - lost - {i})
                    more = list(zip(s.edges(i, some), some)) if some else []
                    e = sorted([t for t in e if t[1] not in lost] + more, key=lambda t: (-t[0], t[1]))[: cfg.M]
                out[i] = e
            new.append(out)
        s.near, s.entry = new, first
        return s.table(g.column("shard")[0].as_py())

    return rows.groupBy("shard").cogroup(graph.groupBy("shard")).applyInArrow(mend, GRAPH)


def save(graph: DataFrame, cfg: IndexConfig, path: str) -> None:
    """Files partitioned by shard and layer, and the settings beside them."""
    graph.write.partitionBy("shard", "layer").mode("overwrite").parquet(f"{path}/graph")
    graph.sparkSession.createDataFrame([(cfg.to_json(),)], "config string").coalesce(1).write.mode("overwrite").json(f"{path}/config")


def load(spark, path: str) -> tuple[DataFrame, IndexConfig]:
    import json

    cfg = IndexConfig(**json.loads(spark.read.schema("config string").json(f"{path}/config").first()[0]))
    return spark.read.parquet(f"{path}/graph"), cfg
