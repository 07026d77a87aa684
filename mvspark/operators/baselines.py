"""Baselines: token gather and re-rank, residual codes, retrieved tokens only, cell probing, pooled vectors.

Tokens are scored where they lie and only the best of every batch and query token go on, so no table of all
pairs of tokens ever exists; objects are scored only where they are candidates.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..config import IndexConfig
from ..functions import kernel
from .routing import score_candidates
from .shards import rows_of
from .similarity import linear_scan, objects, query_block, top_k


def _flat(column) -> np.ndarray:
    """Vectors of an Arrow column of arrays, as rows."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1) if len(column) else np.zeros((0, 1))


def gather(queries: DataFrame, tokens: DataFrame, n: int) -> DataFrame:
    """(qid, q_ix, mv_id, tok_ix, s): the n nearest tokens of every query token; ties by object and token."""
    block = query_block(queries)
    owner = np.concatenate([np.full(len(q), i) for i, (_, q, _) in enumerate(block)]) if block else np.zeros(0, int)
    place = np.concatenate([np.arange(len(q)) for _, q, _ in block]) if block else np.zeros(0, int)
    every = np.concatenate([q for _, q, _ in block]) if block else np.zeros((0, 1))
    ids = np.array([qid for qid, _, _ in block], np.int64)

    def run(batches):
        for b in batches:
            for lo in range(0, b.num_rows if len(every) else 0, 4000):
                some = b.slice(lo, 4000)
                s = every @ _flat(some.column(2)).T
                mv, tok = some.column(0).to_numpy(), some.column(1).to_numpy()
                k = min(n, s.shape[1])
                bar = np.partition(s, s.shape[1] - k, axis=1)[:, s.shape[1] - k]
                row, col = np.nonzero(s >= bar[:, None])  # with all ties of the last
                yield pa.RecordBatch.from_arrays(
                    [pa.array(ids[owner[row]]), pa.array(place[row].astype(np.int32)), pa.array(mv[col]), pa.array(tok[col].astype(np.int32)), pa.array(s[row, col])],
                    names=["qid", "q_ix", "mv_id", "tok_ix", "s"],
                )

    got = tokens.select("mv_id", "tok_ix", "vec").mapInArrow(run, "qid long, q_ix int, mv_id long, tok_ix int, s double")
    w = Window.partitionBy("qid", "q_ix").orderBy(F.desc("s"), "mv_id", "tok_ix")
    return got.withColumn("r", F.row_number().over(w)).where(F.col("r") <= n).drop("r")


def gather_by_graph(queries: DataFrame, tokens: DataFrame, n: int, m: int = 32, ef: int = 40, n_shards: int = 1) -> DataFrame:
    """As ``gather``, by searches of an ordinary layered graph over the tokens of each hashed shard."""
    from .graph import Shard, levels

    block, index, width = query_block(queries), IndexConfig(M=m, ef_construction=ef), max(ef, n)

    def run(t: pa.Table) -> pa.Table:
        mv, tok, x = t.column("mv_id").to_numpy(), t.column("tok_ix").to_numpy(), _flat(t.column("vec"))
        order = np.lexsort((tok, mv))
        mv, tok, x = mv[order], tok[order], x[order]
        g = Shard(index, np.arange(len(x)), x, np.ones(len(x), np.int64)).insert_all(levels(len(x), index))
        rows = [(qid, i, int(mv[j]), int(tok[j]), v) for qid, q, _ in block for i, one in enumerate(q) for v, j in g.nearest(one, width)[:n]]
        kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int32(), pa.float64())
        return pa.Table.from_arrays([pa.array([r[k] for r in rows], kind) for k, kind in enumerate(kinds)], names=["qid", "q_ix", "mv_id", "tok_ix", "s"])

    cut = tokens.select("mv_id", "tok_ix", "vec", F.pmod(F.xxhash64("mv_id"), F.lit(n_shards)).alias("part"))
    got = cut.groupBy("part").applyInArrow(run, "qid long, q_ix int, mv_id long, tok_ix int, s double")
    w = Window.partitionBy("qid", "q_ix").orderBy(F.desc("s"), "mv_id", "tok_ix")
    return got.withColumn("r", F.row_number().over(w)).where(F.col("r") <= n).drop("r")


def rerank(queries: DataFrame, tokens: DataFrame, pairs: DataFrame, k: int, gamma: int = 1) -> DataFrame:
    """Candidates (qid, mv_id) scored exactly: only their objects are assembled."""
    some = tokens.join(pairs.select("mv_id").distinct(), "mv_id", "left_semi")
    return top_k(score_candidates(queries, objects(some, 1), pairs, gamma), k)


def token_gather_rerank(queries: DataFrame, tokens: DataFrame, k: int, alpha: float = 0.5, gamma: int = 1, how: str = "exact", **graph) -> DataFrame:
    """Owners of the alpha*k nearest tokens of each query token, re-ranked exactly; ``how`` is exact or graph."""
    find = {"exact": gather, "graph": gather_by_graph}[how]
    owners = find(queries, tokens, max(1, int(np.ceil(alpha * k))), **graph).select("qid", "mv_id").distinct()
    return rerank(queries, tokens, owners, k, gamma)


def retrieved_only(queries: DataFrame, tokens: DataFrame, k: int, n: int, gamma: int = 1, missing: str = "zero", how: str = "exact", **graph) -> DataFrame:
    """Scores from the gathered tokens alone; what was not gathered counts zero or the lowest gathered score."""
    got = {"exact": gather, "graph": gather_by_graph}[how](queries, tokens, n, **graph)
    w = Window.partitionBy("qid", "q_ix", "mv_id").orderBy(F.desc("s"), "tok_ix")
    best = got.withColumn("r", F.row_number().over(w)).where(F.col("r") <= gamma)
    best = best.groupBy("qid", "q_ix", "mv_id").agg((F.sum("s") / gamma).alias("s"))
    if missing == "floor":
        low = got.groupBy("qid", "q_ix").agg(F.min("s").alias("low"))
        base = low.groupBy("qid").agg(F.sum("low").alias("base"))
        gain = best.join(low, ["qid", "q_ix"]).groupBy("qid", "mv_id").agg(F.sum(F.col("s") - F.col("low")).alias("gain"))
        return top_k(gain.join(base, "qid").select("qid", "mv_id", (F.col("gain") + F.col("base")).alias("score")), k)
    return top_k(best.groupBy("qid", "mv_id").agg(F.sum("s").alias("score")), k)


# --- cells and residual codes ---


@dataclass(frozen=True)
class Cells:
    """Cell centres, and for every coordinate the cuts of the residual and the value that stands for each step."""

    centres: np.ndarray
    cuts: np.ndarray  # d x (2^bits - 1)
    values: np.ndarray  # d x 2^bits

    def nearest(self, x: np.ndarray) -> np.ndarray:
        return (x @ self.centres.T - 0.5 * (self.centres**2).sum(1)).argmax(1)

    def encode(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        cell = self.nearest(x)
        r = x - self.centres[cell]
        code = np.empty(x.shape, np.uint8)
        for j in range(x.shape[1]):
            code[:, j] = np.searchsorted(self.cuts[j], r[:, j], side="right")
        return cell, code

    def decode(self, cell: np.ndarray, code: np.ndarray) -> np.ndarray:
        return self.centres[cell] + self.values[np.arange(code.shape[1]), code]


def fit_cells(tokens: DataFrame, n: int, bits: int, rounds: int = 5) -> Cells:
    """n centres by Lloyd rounds, and quantile steps of the residuals, from a sample of fixed size spread by hash."""
    some = tokens.orderBy(F.xxhash64("mv_id", "tok_ix"), "mv_id", "tok_ix").limit(n * 40).select("vec").toArrow()
    x = _flat(some.column("vec"))
    c = x[:n].copy()
    for _ in range(rounds):
        g = (x @ c.T - 0.5 * (c**2).sum(1)).argmax(1)
        c = np.array([x[g == i].mean(0) if (g == i).any() else c[i] for i in range(len(c))])
    r = x - c[(x @ c.T - 0.5 * (c**2).sum(1)).argmax(1)]
    steps = 1 << bits
    cuts = np.quantile(r, np.arange(1, steps) / steps, axis=0).T
    values = np.quantile(r, (np.arange(steps) + 0.5) / steps, axis=0).T
    return Cells(c, np.ascontiguousarray(cuts), np.ascontiguousarray(values))


def encode(tokens: DataFrame, cells: Cells) -> DataFrame:
    """(mv_id, tok_ix, cell, code): nearest centre and the step of every coordinate's residual."""

    def run(batches):
        for b in batches:
            cell, code = cells.encode(_flat(b.column(2))) if b.num_rows else (np.zeros(0, int), np.zeros((0, 1), np.uint8))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(cell.astype(np.int32)), pa.array([r.tobytes() for r in code], pa.binary())], names=["mv_id", "tok_ix", "cell", "code"])

    return tokens.select("mv_id", "tok_ix", "vec").mapInArrow(run, "mv_id long, tok_ix int, cell int, code binary")


def probes(queries: DataFrame, cells: Cells, codes: DataFrame, n: int, t_prime: int | None = None) -> tuple[pd.DataFrame, dict[int, np.ndarray]]:
    """(qid, q_ix, cell) to look at, and every query token's score for objects that it does not meet.

    That score is the centre's score of the cell at which the sizes of the best cells first reach ``t_prime`` tokens.
    """
    size = np.zeros(len(cells.centres), np.int64)
    for cell, count in codes.groupBy("cell").count().collect():  # a row a cell
        size[cell] = count
    rows, missing = [], {}
    for qid, q, _ in query_block(queries):
        s = q @ cells.centres.T
        order = np.argsort(-s, axis=1, kind="stable")
        reached = np.cumsum(size[order], axis=1)
        at = (reached < (t_prime if t_prime is not None else 0)).sum(1) if t_prime is not None else np.full(len(q), min(n, len(size) - 1))
        missing[qid] = s[np.arange(len(q)), order[np.arange(len(q)), np.minimum(at, len(size) - 1)]]
        rows += [(qid, i, int(c)) for i in range(len(q)) for c in order[i, :n]]
    return pd.DataFrame(rows, columns=["qid", "q_ix", "cell"]), missing


def ivf_probe(queries: DataFrame, codes: DataFrame, cells: Cells, k: int, n_probe: int = 32, t_prime: int = 40_000, gamma: int = 1) -> DataFrame:
    """Cells near each query token; scores from residual codes; tokens not met count as the score at ``t_prime`` tokens.

    A query token's part of an object is the mean of its gamma best decoded tokens there, places left counting as not met. An
    object is scored where it lies, with all its codes; those without a token in a probed cell are no answers.
    """
    ask, missing = probes(queries, cells, codes, n_probe, t_prime)
    block = query_block(queries)
    looked = {qid: np.zeros((len(q), len(cells.centres)), bool) for qid, q, _ in block}
    for qid, some in ask.groupby("qid"):
        looked[qid][some["q_ix"].to_numpy(), some["cell"].to_numpy()] = True

    def run(batches):
        for b in batches:
            for lo in range(0, b.num_rows, 256):
                some = b.slice(lo, 256)
                ids, size = some.column(0).to_numpy(), np.asarray(some.column(1).value_lengths(), np.int64)
                cell = some.column(1).flatten().to_numpy()
                x = cells.decode(cell, np.stack([np.frombuffer(c, np.uint8) for c in some.column(2).flatten().to_pylist()]))
                met, out = kernel.Block(x, size), []
                for qid, q, w in block:
                    near = looked[qid][:, cell]
                    hit = np.flatnonzero(np.logical_or.reduceat(near.any(0), met.start))
                    gain = np.where(near, np.maximum(q @ x.T - missing[qid][:, None], 0), 0)
                    s = w @ met._best(gain, met.start, met.size, gamma)[:, hit] + float(w @ missing[qid])
                    best = np.lexsort((ids[hit], -s))[:k]
                    out.append((np.full(len(best), qid), ids[hit][best], s[best]))
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*out)], names=["qid", "mv_id", "score"])

    whole = codes.groupBy("mv_id").agg(F.array_sort(F.collect_list(F.struct("tok_ix", "cell", "code"))).alias("t"))
    whole = whole.select("mv_id", F.col("t.cell").alias("cell"), F.col("t.code").alias("code"))
    return top_k(whole.mapInArrow(run, "qid long, mv_id long, score double"), k)


def residual_centroid(queries: DataFrame, codes: DataFrame, cells: Cells, k: int, n_probe: int = 4, n_candidates: int | None = None, gamma: int = 1) -> DataFrame:
    """Objects with a token in a probed cell, thinned by scores of their cells' centres, then scored on decoded tokens."""
    ask, _ = probes(queries, cells, codes, n_probe)
    block = query_block(queries)
    spark = codes.sparkSession
    asked = spark.createDataFrame(ask[["qid", "cell"]].drop_duplicates(), "qid long, cell int") if len(ask) else spark.createDataFrame([], "qid long, cell int")
    pairs = codes.select("mv_id", "cell").distinct().join(F.broadcast(asked), "cell").select("qid", "mv_id").distinct()
    whole = codes.groupBy("mv_id").agg(F.array_sort(F.collect_list(F.struct("tok_ix", "cell", "code"))).alias("t"))
    whole = whole.select("mv_id", F.col("t.cell").alias("cell"), F.col("t.code").alias("code"))
    queries_of = pairs.groupBy("mv_id").agg(F.collect_list("qid").alias("by"))
    met = whole.join(queries_of, "mv_id")
    by_id = {qid: (q, w, q @ cells.centres.T) for qid, q, w in block}

    def rough(batches):
        for b in batches:
            out = []
            for mv, cell, by in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(3).to_pylist()):
                for qid in by:
                    _, w, s = by_id[qid]
                    out.append((qid, mv, float(w @ kernel.top_sums(s[:, cell], gamma))))
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], t) for i, t in enumerate((pa.int64(), pa.int64(), pa.float64()))], names=["qid", "mv_id", "score"])

    def fine(batches):
        for b in batches:
            out = []
            for mv, cell, code, by in zip(*(b.column(i).to_pylist() for i in range(4))):
                x = cells.decode(np.array(cell), np.stack([np.frombuffer(c, np.uint8) for c in code]))
                for qid in by:
                    q, w, _ = by_id[qid]
                    out.append((qid, mv, float(w @ kernel.top_sums(q @ x.T, gamma))))
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], t) for i, t in enumerate((pa.int64(), pa.int64(), pa.float64()))], names=["qid", "mv_id", "score"])

    schema = "qid long, mv_id long, score double"
    best = top_k(met.mapInArrow(rough, schema), n_candidates or 4 * k).select("qid", "mv_id")
    some = whole.join(best.groupBy("mv_id").agg(F.collect_list("qid").alias("by")), "mv_id")
    return top_k(some.select("mv_id", "cell", "code", "by").mapInArrow(fine, schema), k)


def cell_probe(queries: DataFrame, tokens: DataFrame, k: int, n_cells: int = 64, n_probe: int = 8, bits: int = 4, gamma: int = 1, t_prime: int | None = None, residual: bool = False) -> DataFrame:
    """Both forms with cells made for this call; ``t_prime`` is the printed 40 000 scaled by the tokens there are."""
    cells = fit_cells(tokens, n_cells, bits)
    codes = encode(tokens, cells)
    if residual:
        return residual_centroid(queries, codes, cells, k, n_probe, gamma=gamma)
    return ivf_probe(queries, codes, cells, k, n_probe, t_prime if t_prime is not None else max(k, tokens.count() // 100), gamma)


# --- one vector an object, and single vectors ---


def mean_pool(tokens: DataFrame) -> DataFrame:
    """(mv_id, vec): mean of an object's token vectors."""
    flat = tokens.select("mv_id", F.posexplode("vec").alias("i", "x")).groupBy("mv_id", "i").agg(F.avg("x").alias("x"))
    return flat.groupBy("mv_id").agg(F.array_sort(F.collect_list(F.struct("i", "x"))).alias("v")).select("mv_id", F.col("v.x").alias("vec"))


def knn(queries: DataFrame, tokens: DataFrame, k: int) -> DataFrame:
    """(qid, q_ix, rank, mv_id, tok_ix, s): exact nearest tokens of every query token."""
    w = Window.partitionBy("qid", "q_ix").orderBy(F.desc("s"), "mv_id", "tok_ix")
    return gather(queries, tokens, k).withColumn("rank", F.row_number().over(w))


def pooled_top(queries: DataFrame, tokens: DataFrame, k: int) -> DataFrame:
    """One vector an object: inner products of means."""
    q = mean_pool(queries.select(F.col("qid").alias("mv_id"), F.col("q_ix").alias("tok_ix"), "vec"))
    q = q.select(F.col("mv_id").alias("qid"), F.lit(0).alias("q_ix"), "vec")
    near = gather(q, mean_pool(tokens).withColumn("tok_ix", F.lit(0)), k)
    return top_k(near.select("qid", "mv_id", F.col("s").alias("score")), k)


def pooled_rerank(queries: DataFrame, tokens: DataFrame, k: int, prefetch: int = 4, gamma: int = 1) -> DataFrame:
    """A database's way: pooled candidates, then exact multi-vector scores."""
    some = pooled_top(queries, tokens, prefetch * k).select("qid", "mv_id")
    return rerank(queries, tokens, some, k, gamma)


def brute_force(queries: DataFrame, objs: DataFrame, k: int, gamma: int = 1) -> DataFrame:
    return linear_scan(queries, objs, k, gamma)


def product_quantised(queries: DataFrame, tokens: DataFrame, k: int, parts: int = 8, words: int = 16) -> DataFrame:
    """Single-vector search by product quantisation: codes of sub-vectors, scores by table look-up.

    Results name tokens: qid and mv_id are id * 1000 + place.
    """
    some = tokens.orderBy(F.xxhash64("mv_id", "tok_ix"), "mv_id", "tok_ix").limit(words * 60).select("vec").collect()
    x = np.array([r.vec for r in some], float)
    width = x.shape[1] // parts
    books = []
    for p in range(parts):
        y = x[:, p * width : (p + 1) * width if p < parts - 1 else None]
        c = y[:words].copy()
        for _ in range(6):
            g = (y @ c.T - 0.5 * (c**2).sum(1)).argmax(1)
            c = np.array([y[g == i].mean(0) if (g == i).any() else c[i] for i in range(len(c))])
        books.append(c)
    cut = lambda v, p: v[:, p * width : (p + 1) * width if p < parts - 1 else None]
    block = [(qid * 1000 + i, v[None]) for qid, q, _ in query_block(queries) for i, v in enumerate(q)]

    def run(frames):
        for f in frames:
            v = np.array(f["vec"].tolist(), float)
            codes = np.stack([(cut(v, p) @ b.T - 0.5 * (b**2).sum(1)).argmax(1) for p, b in enumerate(books)])
            ids = f["mv_id"].to_numpy() * 1000 + f["tok_ix"].to_numpy()
            for name, q in block:
                s = sum((cut(q, p) @ b.T)[0][codes[p]] for p, b in enumerate(books))
                best = np.lexsort((ids, -s))[:k]
                yield pd.DataFrame({"qid": name, "mv_id": ids[best], "score": s[best]})

    return top_k(tokens.select("mv_id", "tok_ix", "vec").mapInPandas(run, "qid long, mv_id long, score double"), k)
