"""Scores of queries against objects, in set form and as a scan of Arrow blocks.

Tokens: (mv_id, tok_ix, vec array<double>). Queries: (qid, q_ix, vec[, weight]).
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..config import SimConfig
from ..functions import kernel
from ..functions.vectors import norm
from .shards import rows_of

#: query values that may be held by every task (32 M doubles); more are scored in blocks
QUERY_VALUES = 32_000_000


def normalised(tokens: DataFrame) -> DataFrame:
    """Tokens of unit length; zero vectors stay as they are."""
    size = norm(F.col("vec"))
    return tokens.withColumn("vec", F.when(size > 0, F.transform("vec", lambda x: x / size)).otherwise(F.col("vec")))


def objects(tokens: DataFrame, min_tokens: int = 2, unit: bool = False) -> DataFrame:
    """Nested form (mv_id, n_tok, vecs), objects below ``min_tokens`` dropped; ``unit`` normalises every token."""
    tokens = normalised(tokens) if unit else tokens
    nested = tokens.groupBy("mv_id").agg(F.array_sort(F.collect_list(F.struct("tok_ix", "vec"))).alias("t"))
    return nested.select("mv_id", F.size("t").alias("n_tok"), F.col("t.vec").alias("vecs")).where(F.col("n_tok") >= min_tokens)


def to_tokens(objs: DataFrame) -> DataFrame:
    return objs.select("mv_id", F.posexplode("vecs").alias("tok_ix", "vec"))


def query_block(queries: DataFrame, limit: int = QUERY_VALUES) -> list[tuple[int, np.ndarray, np.ndarray]]:
    """Queries as (qid, matrix, weights); a query set is small and checked to be."""
    rows = queries.groupBy("qid").agg(F.array_sort(F.collect_list(F.struct("q_ix", "vec", *(["weight"] if "weight" in queries.columns else [])))).alias("t"))
    size = rows.agg(F.sum(F.size("t") * F.size(F.col("t")[0]["vec"]))).first()[0] or 0
    if size > limit:
        raise ValueError(f"the query set holds {size} values; search it in parts of {limit}")
    out = []
    got = rows.select("qid", F.col("t.vec").alias("vecs"), *([F.col("t.weight").alias("w")] if "weight" in queries.columns else [])).orderBy("qid").toArrow()  # a few bytes a value
    for b in got.to_batches():
        x, n = rows_of(b.column(1))
        end = np.cumsum(n)
        for i, (qid, hi) in enumerate(zip(b.column(0).to_pylist(), end.tolist())):
            w = np.array(b.column(2)[i].as_py(), float) if b.num_columns > 2 else np.ones(int(n[i]))
            if (w < 0).any():
                raise ValueError("token weights must not be negative")
            out.append((qid, np.array(x[hi - n[i] : hi], float), w))
    return out


def held(objs: DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray, list | None]:
    """(ids, tokens as rows, tokens of each object, groups) of objects in order of ids, for tasks that hold them all."""
    t = objs.select("mv_id", "vecs", *(["groups"] if "groups" in objs.columns else [])).toArrow()
    ids = t.column("mv_id").to_numpy()
    x, size = rows_of(t.column("vecs"))
    order = np.argsort(ids, kind="stable")
    start = np.cumsum(size) - size
    groups = [np.array(g) for g in t.column("groups").take(order).to_pylist()] if "groups" in objs.columns else None
    return ids[order], x[kernel.spans(start[order], size[order])], size[order], groups


def values_of(objs: DataFrame) -> int:
    """Coordinates of all tokens."""
    return objs.agg(F.sum(F.size("vecs") * F.size(F.col("vecs")[0]))).first()[0] or 0


def token_scores(queries: DataFrame, tokens: DataFrame, metric: str = "ip") -> DataFrame:
    """(qid, q_ix, mv_id, tok_ix, s) of every query token and token, by block products."""
    block = query_block(queries)

    def run(frames):
        for f in frames:
            for i in range(0, len(f), 2000):
                some = f.iloc[i : i + 2000]
                v = np.array(some["vec"].tolist(), float)
                for qid, q, _ in block:
                    s = kernel.similarities(q, v, metric)
                    n, m = s.shape
                    yield pd.DataFrame({"qid": qid, "q_ix": np.repeat(np.arange(n), m), "mv_id": np.tile(some["mv_id"], n),
                                        "tok_ix": np.tile(some["tok_ix"], n), "s": s.ravel()})

    return tokens.select("mv_id", "tok_ix", "vec").mapInPandas(run, "qid long, q_ix int, mv_id long, tok_ix int, s double")


def gamma_nn(scores: DataFrame, gamma: int) -> DataFrame:
    """The gamma nearest tokens of each object for each query token; ties by token."""
    w = Window.partitionBy("qid", "q_ix", "mv_id").orderBy(F.desc("s"), "tok_ix")
    return scores.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= gamma)


def unified(scores: DataFrame, gamma: int = 1, short: str = "literal", weights: DataFrame | None = None) -> DataFrame:
    """(qid, mv_id, score): weighted sum over query tokens of the mean of their gamma nearest."""
    near = gamma_nn(scores, gamma).groupBy("qid", "q_ix", "mv_id").agg(F.sum("s").alias("s"), F.count("*").alias("n"))
    by = F.lit(gamma) if short == "literal" else F.col("n")
    near = near.withColumn("s", F.col("s") / by)
    if weights is not None:
        near = near.join(F.broadcast(weights.select("qid", "q_ix", "weight")), ["qid", "q_ix"]).withColumn("s", F.col("s") * F.col("weight"))
    return near.groupBy("qid", "mv_id").agg(F.sum("s").alias("score"))


def top_k(scores: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("qid").orderBy(F.desc("score"), "mv_id")
    return scores.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("qid", "rank", "mv_id", "score")


def each_query(queries: DataFrame, objs: DataFrame, work, schema: str, more: tuple = (), step: int = 256) -> DataFrame:
    """Rows of ``work`` for every query and every object, with all tokens of both at hand, so that no table of token scores is dealt out.

    ``work`` (objects as a block, their ids, their columns ``more``) is called for ``step`` objects at a time and gives a
    function of (qid, tokens, token weights, scores of query tokens and objects' tokens) that gives the columns of ``schema``.
    """
    block = query_block(queries)
    names = [c.split()[0] for c in schema.split(", ")]

    def run(batches):
        for b in batches:
            for lo in range(0, b.num_rows, step):
                some = b.slice(lo, step)
                met, ids = kernel.Block(*rows_of(some.column(1))), some.column(0).to_numpy()
                one = work(met, ids, some.columns[2:])
                for qid, q, w in block:
                    cols = one(qid, q, w, q @ met.x.T)
                    if len(cols[-1]):
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(cols[-1]), qid)), *map(pa.array, cols)], names=names)

    return objs.select("mv_id", "vecs", *more).mapInArrow(run, schema)


def nearest_tokens(queries: DataFrame, objs: DataFrame, gamma: int) -> DataFrame:
    """As ``gamma_nn`` of all token scores, object by object; tokens are named by their place."""

    def work(met, ids, _):
        def one(qid, q, w, s):
            out = []
            for at, cube in kernel.cubes(s, met.start, met.size):
                g = min(gamma, cube.shape[2])
                pick = np.argsort(-cube, axis=2, kind="stable")[:, :, :g]
                shape = pick.shape
                spread = lambda x, axis: np.broadcast_to(x.reshape([-1 if a == axis else 1 for a in range(3)]), shape).ravel()
                out.append((spread(np.arange(len(q), dtype=np.int32), 0), spread(ids[at], 1), pick.ravel().astype(np.int32), np.take_along_axis(cube, pick, 2).ravel(), spread(np.arange(1, g + 1, dtype=np.int32), 2)))
            return [np.concatenate(c) for c in zip(*out)]

        return one

    return each_query(queries, objs, work, "qid long, q_ix int, mv_id long, tok_ix int, s double, rank int")


def _groups_of(groups: DataFrame) -> dict[int, np.ndarray]:
    """Group of every token of each query; as few rows as the query set has tokens."""
    out: dict[int, dict[int, int]] = {}
    for r in groups.select("qid", "q_ix", "g").collect():
        out.setdefault(r.qid, {})[r.q_ix] = r.g
    return {qid: np.array([by[i] for i in sorted(by)]) for qid, by in out.items()}


def _short(cube: np.ndarray, own: np.ndarray, named: np.ndarray, beta: int) -> np.ndarray:
    """Groups x objects x beta: places of the tokens nearest to the centre of each group."""
    near = np.tensordot((own[None] == named[:, None]).astype(float), cube, 1)  # a sum of members is a centre
    return np.argsort(-near, axis=2, kind="stable")[:, :, :beta]


def shortlisted(queries: DataFrame, objs: DataFrame, groups: DataFrame, beta: int) -> DataFrame:
    """As ``shortlists`` of all token scores, object by object."""
    by = _groups_of(groups)

    def work(met, ids, _):
        def one(qid, q, w, s):
            named, out = np.unique(by[qid]), []
            for at, cube in kernel.cubes(s, met.start, met.size):
                pick = _short(cube, by[qid], named, beta)
                g, o = np.meshgrid(named, ids[at], indexing="ij")
                out.append((np.repeat(g.ravel(), pick.shape[2]).astype(np.int32), np.repeat(o.ravel(), pick.shape[2]), pick.ravel().astype(np.int32)))
            return [np.concatenate(c) for c in zip(*out)]

        return one

    return each_query(queries, objs, work, "qid long, g int, mv_id long, tok_ix int")


def refined_scores(queries: DataFrame, objs: DataFrame, groups: DataFrame, beta: int, gamma: int = 1) -> DataFrame:
    """As ``refined`` with the shortlists of all token scores, object by object."""
    by = _groups_of(groups)

    def work(met, ids, _):
        def one(qid, q, w, s):
            named, mine = np.unique(by[qid], return_inverse=True)
            out = []
            for at, cube in kernel.cubes(s, met.start, met.size):
                got = np.take_along_axis(cube, _short(cube, by[qid], named, beta)[mine], 2)
                g = min(gamma, got.shape[2])
                out.append((ids[at], (np.partition(got, got.shape[2] - g, axis=2)[:, :, got.shape[2] - g :].sum(2) / gamma).sum(0)))
            return [np.concatenate(c) for c in zip(*out)]

        return one

    return each_query(queries, objs, work, "qid long, mv_id long, score double")


def linear_scan(
    queries: DataFrame, objs: DataFrame, k: int, gamma: int = 1, metric="ip", short: str = "literal", where: Column | None = None, mode: str = "exact",
    beta: int | None = None,
) -> DataFrame:
    """Exact top-k (ground truth): every object scored where it lies, k rows a batch and query go on."""
    sim = SimConfig(metric=metric, gamma=gamma, short=short, mode=mode, beta=beta)
    block = query_block(queries)
    groups = {qid: kernel.cluster_tokens(q) for qid, q, _ in block} if mode == "clustered" else {}
    metric = kernel.metric_of(sim.metric)

    def run(batches):
        for b in batches:
            ids = b.column(0).to_numpy()
            if not len(ids) or not block:
                continue
            objects_, every, out = kernel.Block(*rows_of(b.column(1))), np.arange(len(ids)), []
            for qid, q, w in block:
                if mode == "clustered":
                    s = objects_.clustered_scores(q, groups[qid], every, gamma, w, beta)
                else:
                    s = objects_.scores(q, every, gamma, w, metric, short)
                best = np.lexsort((ids, -s))[:k]
                out.append((np.full(len(best), qid), ids[best], s[best]))
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*out)], names=["qid", "mv_id", "score"])

    kept = objs if where is None else objs.where(where)
    return top_k(kept.select("mv_id", "vecs").mapInArrow(run, "qid long, mv_id long, score double"), k)


def cluster_objects(objs: DataFrame, rounds: int = 5) -> DataFrame:
    """``objs`` with ``groups``: the group of each token, made once an object and kept with it."""
    cols = [c for c in objs.columns if c != "groups"]
    kinds = ", ".join(f"{n} {t}" for n, t in objs.select(cols).dtypes)
    at = cols.index("vecs")

    def run(batches):
        for b in batches:
            x, size = rows_of(b.column(at))
            start = np.cumsum(size) - size
            got = [kernel.cluster_tokens(x[i : i + n], rounds=rounds).astype(np.int32) for i, n in zip(start.tolist(), size.tolist())]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(got, pa.list_(pa.int32()))], names=[*cols, "groups"])

    return objs.select(cols).mapInArrow(run, f"{kinds}, groups array<int>")


def object_clusters(objs: DataFrame) -> DataFrame:
    """(mv_id, cluster, centroid, members): the groups of each object's tokens as rows."""
    o = objs if "groups" in objs.columns else cluster_objects(objs)
    t = o.select("mv_id", F.posexplode(F.arrays_zip("groups", "vecs")).alias("tok_ix", "t")).select("mv_id", F.col("t.groups").alias("cluster"), "tok_ix", F.col("t.vecs").alias("vec"))
    part = t.select("mv_id", "cluster", "tok_ix", F.posexplode("vec").alias("i", "x")).groupBy("mv_id", "cluster", "i").agg(F.avg("x").alias("x"))
    centre = part.groupBy("mv_id", "cluster").agg(F.array_sort(F.collect_list(F.struct("i", "x")))["x"].alias("centroid"))
    members = t.groupBy("mv_id", "cluster").agg(F.array_sort(F.collect_list("tok_ix")).alias("members"))
    return centre.join(members, ["mv_id", "cluster"])


def shortlists(scores: DataFrame, groups: DataFrame, beta: int) -> DataFrame:
    """(qid, g, mv_id, tok_ix): the beta tokens of each object nearest to the centre of each group (qid, q_ix, g) of query tokens."""
    s = scores.join(groups.select("qid", "q_ix", "g"), ["qid", "q_ix"])
    near = s.groupBy("qid", "g", "mv_id", "tok_ix").agg(F.sum("s").alias("c"))  # a sum of members is a centre
    w = Window.partitionBy("qid", "g", "mv_id").orderBy(F.desc("c"), "tok_ix")
    return near.withColumn("r", F.row_number().over(w)).where(F.col("r") <= beta).select("qid", "g", "mv_id", "tok_ix")


def refined(scores: DataFrame, groups: DataFrame, short: DataFrame, gamma: int = 1) -> DataFrame:
    """(qid, mv_id, score): the unified similarity where each query token looks at its group's shortlist only.

    Groups are rows, so the groups of one pair are worked on by different tasks.
    """
    s = scores.join(groups.select("qid", "q_ix", "g"), ["qid", "q_ix"]).join(short, ["qid", "g", "mv_id", "tok_ix"], "left_semi")
    return unified(s.select("qid", "q_ix", "mv_id", "tok_ix", "s"), gamma)


def score_pairs(left: DataFrame, right: DataFrame, pairs: DataFrame, kind: str = "fused", gamma: int = 1, clustered: bool = False, beta: int | None = None) -> DataFrame:
    """(src, dst, weight) for candidate pairs (src, dst) of objects: partners of one object are scored by one product.

    Tasks hold a right side of up to ``QUERY_VALUES`` values, so that vectors don't travel with every pair. Objects without
    ``groups`` are clustered once each before they meet.
    """
    if kind not in kernel.EDGES:
        raise ValueError(f"unknown edge function {kind!r}")
    if not clustered and values_of(right) <= QUERY_VALUES:
        return _pairs_asked(left, right, pairs, kind, gamma)
    if clustered:
        left, right = (o if "groups" in o.columns else cluster_objects(o) for o in (left, right))
    none = F.lit(None).cast("array<int>")

    def run(batches):
        for b in batches:
            src, dst = b.column(0).to_numpy(), b.column(1).to_numpy()
            x, sx = rows_of(b.column(2))
            y, sy = rows_of(b.column(3))
            at, w, n = np.cumsum(sx) - sx, np.zeros(len(src)), len(src)
            own = b.column(4).to_pylist() if clustered else None
            other = b.column(5).to_pylist() if clustered else None
            edge = np.flatnonzero(np.concatenate([[True], src[1:] != src[:-1], [True]])) if n else []
            first_y = np.cumsum(sy) - sy
            for lo, hi in zip(edge[:-1], edge[1:]):
                u = x[at[lo] : at[lo] + sx[lo]]
                end = first_y[hi - 1] + sy[hi - 1]
                met = kernel.Block(np.concatenate([u, y[first_y[lo] : end]]), np.concatenate([[len(u)], sy[lo:hi]]))
                if clustered:
                    met.groups = {0: np.array(own[lo]), **{1 + k: np.array(g) for k, g in enumerate(other[lo:hi])}}
                w[lo:hi] = met.edges(0, np.arange(1, hi - lo + 1), gamma, kind, clustered, beta)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(w)], names=["src", "dst", "weight"])

    side = lambda o, i, v, g: o.select(F.col("mv_id").alias(i), F.col("vecs").alias(v), (F.col("groups") if clustered else none).alias(g))
    met = pairs.join(side(right, "dst", "v", "gv"), "dst").join(side(left, "src", "u", "gu"), "src")
    met = met.select("src", "dst", "u", "v", "gu", "gv").sortWithinPartitions("src")
    return met.mapInArrow(run, "src long, dst long, weight double")


def _pairs_asked(left, right, pairs, kind, gamma) -> DataFrame:
    ids, x, size, _ = held(right)
    every = left.sparkSession.sparkContext.broadcast((ids, x, size))

    def run(batches):
        ids, x, size = every.value
        met = kernel.Block(x, size)
        for b in batches:
            y, n = rows_of(b.column(1))
            end = np.cumsum(n)
            for i, (src, hi) in enumerate(zip(b.column(0).to_pylist(), end.tolist())):
                to = b.column(2)[i].values.to_numpy()
                at = np.minimum(np.searchsorted(ids, to), len(ids) - 1) if len(ids) else np.zeros(0, np.int64)
                at = at[ids[at] == to] if len(ids) else at
                w = met.weights(y[hi - n[i] : hi], at, gamma, kind)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), src)), pa.array(ids[at]), pa.array(w)], names=["src", "dst", "weight"])

    asked = pairs.groupBy("src").agg(F.collect_list("dst").alias("to"))  # at most the ids of the right side, which is bounded
    met = left.select(F.col("mv_id").alias("src"), "vecs").join(asked, "src").select("src", "vecs", "to")
    return met.mapInArrow(run, "src long, dst long, weight double")


def every_pair(
    left: DataFrame, right: DataFrame, kind: str = "fused", gamma: int = 1, clustered: bool = False, beta: int | None = None, other=None, keep: int | None = None, skip_own: bool = False,
    sizes: bool = False,
) -> DataFrame:
    """(src, dst, weight[, other][, n]) of all pairs: tasks hold ``right`` and score each object of ``left`` against all of it by one product.

    ``other`` (u, block, weights) gives a second value of the same pairs, so that two weights are compared where they arise; ``keep`` leaves each
    src its best, ties by dst; ``sizes`` adds the tokens of src. A right side above ``QUERY_VALUES`` is worked on part by part.
    """
    if kind not in kernel.EDGES:
        raise ValueError(f"unknown edge function {kind!r}")
    if clustered:
        left, right = (o if "groups" in o.columns else cluster_objects(o) for o in (left, right))
    parts = max(1, -(-values_of(right) // QUERY_VALUES))
    if parts > 1:
        some = [right.where(F.pmod(F.xxhash64("mv_id"), F.lit(parts)) == i) for i in range(parts)]
        out = None
        for r in some:
            one = _pairs_held(left, r, kind, gamma, clustered, beta, other, keep, skip_own, sizes)
            out = one if out is None else out.unionByName(one)
        if keep is None:
            return out
        w = Window.partitionBy("src").orderBy(F.desc("weight"), "dst")
        return out.withColumn("r", F.row_number().over(w)).where(F.col("r") <= keep).drop("r")
    return _pairs_held(left, right, kind, gamma, clustered, beta, other, keep, skip_own, sizes)


def _pairs_held(left, right, kind, gamma, clustered, beta, other, keep, skip_own, sizes) -> DataFrame:
    ids, x, size, groups = held(right)
    every = left.sparkSession.sparkContext.broadcast((ids, x, size, groups))
    names = ["src", "dst", "weight", *(["other"] if other else []), *(["n"] if sizes else [])]

    def run(batches):
        ids, x, size, groups = every.value
        met = kernel.Block(x, size)
        if groups:
            met.groups = dict(enumerate(groups))
        for b in batches:
            y, n = rows_of(b.column(1))
            end = np.cumsum(n)
            for i, (src, hi) in enumerate(zip(b.column(0).to_pylist(), end.tolist())):
                if not len(ids):
                    continue
                u = y[hi - n[i] : hi]
                w = met.clustered_weights(u, np.array(b.column(2)[i].as_py()), gamma, kind, beta) if clustered else met.weights(u, None, gamma, kind)
                cols = [ids, w, *([other(u, met, w)] if other else [])]
                if skip_own:
                    cols = [c[ids != src] for c in cols]
                if keep is not None and len(cols[0]) > keep:
                    best = np.lexsort((cols[0], -cols[1]))[:keep]
                    cols = [c[best] for c in cols]
                if sizes:
                    cols.append(np.full(len(cols[0]), n[i], np.int32))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(cols[0]), src)), *map(pa.array, cols)], names=names)

    schema = "src long, dst long, weight double" + ", other double" * bool(other) + ", n int" * sizes
    return left.select("mv_id", "vecs", *(["groups"] if clustered else [])).mapInArrow(run, schema)


def pairs_in_cells(objs: DataFrame, cells: DataFrame, gamma: int = 1, keep: int | None = None) -> DataFrame:
    """(src, dst, weight) of all pairs of objects that share a cell (mv_id, cell), each once; ``keep`` leaves each src its best, ties by dst.

    Tasks hold the objects in order of cells, so that candidates are never rows: their number grows with the square of a cell.
    Objects above ``QUERY_VALUES`` are held part by part.
    """
    cells = cells.select("mv_id", "cell").distinct()
    left = objs.select("mv_id", "vecs").join(cells.groupBy("mv_id").agg(F.collect_list("cell").alias("cells")), "mv_id")
    parts, out = max(1, -(-values_of(objs) // QUERY_VALUES)), None
    for i in range(parts):
        one = _cells_held(left, objs if parts == 1 else objs.where(F.pmod(F.xxhash64("mv_id"), F.lit(parts)) == i), cells, gamma, keep)
        out = one if out is None else out.unionByName(one)
    if parts == 1 or keep is None:
        return out
    w = Window.partitionBy("src").orderBy(F.desc("weight"), "dst")
    return out.withColumn("r", F.row_number().over(w)).where(F.col("r") <= keep).drop("r")


def _cells_held(left, right, cells, gamma, keep) -> DataFrame:
    ids, x, size, _ = held(right)
    t = cells.join(right.select("mv_id"), "mv_id").toArrow()
    named = t.column("cell").combine_chunks().dictionary_encode()
    at, code = np.searchsorted(ids, t.column("mv_id").to_numpy()), named.indices.to_numpy(zero_copy_only=False)
    order = np.lexsort((at, code))
    at, edge = at[order], np.searchsorted(code[order], np.arange(len(named.dictionary) + 1))
    single = len(np.unique(at)) == len(at)  # then a cell's tokens lie side by side
    if single:
        start = np.cumsum(size) - size
        ids, x, size, at = ids[at], x[kernel.spans(start[at], size[at])], size[at], np.arange(len(at))
    member = {c: at[lo:hi] for c, lo, hi in zip(named.dictionary.to_pylist(), edge[:-1].tolist(), edge[1:].tolist())}
    every = left.sparkSession.sparkContext.broadcast((ids, x, size, member, single))

    def run(batches):
        ids, x, size, member, single = every.value
        whole, own = kernel.Block(x, size), {}

        def block(c):
            if c not in own:
                lo, hi = member[c][0], member[c][-1] + 1
                own[c] = ids[lo:hi], kernel.Block(x[whole.start[lo] : whole.start[hi - 1] + size[hi - 1]], size[lo:hi])
            return own[c]

        for b in batches:
            y, n = rows_of(b.column(1))
            end = np.cumsum(n)
            for i, (src, hi, where) in enumerate(zip(b.column(0).to_pylist(), end.tolist(), b.column(2).to_pylist())):
                where = [c for c in where if c in member]
                if not where:
                    continue
                u = y[hi - n[i] : hi]
                if single and len(where) == 1:
                    dst, met = block(where[0])
                    w = met.weights(u, None, gamma)
                else:
                    some = np.unique(np.concatenate([member[c] for c in where]))
                    dst, w = ids[some], whole.weights(u, some, gamma)
                dst, w = dst[dst != src], w[dst != src]
                if keep is not None and len(dst) > keep:
                    best = np.lexsort((dst, -w))[:keep]
                    dst, w = dst[best], w[best]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(dst), src)), pa.array(dst), pa.array(w)], names=["src", "dst", "weight"])

    return left.mapInArrow(run, "src long, dst long, weight double")


def cosines(tokens: DataFrame, others: DataFrame, digits: int) -> DataFrame:
    """(a, i, b, s): rounded cosine of every token (a, i) and the vector of every row of ``others`` (mv_id, vecs), which tasks hold."""
    ids, y, _, _ = held(others)
    every = tokens.sparkSession.sparkContext.broadcast((ids, y))

    def run(batches):
        ids, y = every.value
        size = np.sqrt((y * y).sum(1))
        for b in batches:
            for lo in range(0, b.num_rows if len(ids) else 0, 16):
                some = b.slice(lo, 16)
                x = some.column(2).flatten().to_numpy(zero_copy_only=False).reshape(some.num_rows, -1)
                with np.errstate(divide="ignore", invalid="ignore"):
                    s = (x @ y.T / (np.sqrt((x * x).sum(1))[:, None] * size)).ravel() * 10.0**digits
                s = np.copysign(np.floor(np.abs(s) + 0.5), s) / 10.0**digits + 0.0
                a, i = (np.repeat(some.column(c).to_numpy(), len(ids)) for c in (0, 1))
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(i), pa.array(np.tile(ids, some.num_rows)), pa.array(s)], names=["a", "i", "b", "s"])

    return tokens.select("mv_id", "tok_ix", "vec").mapInArrow(run, "a long, i int, b long, s double")


def gap_excess(queries: DataFrame):
    """For ``every_pair`` over unit vectors: by how much the gap of two objects' scores exceeds 2 |Q| sqrt((1 - weight) max(|u|, |v|)), over all queries.

    A gap is 2 |Q| at most, so only pairs with a smaller bound are looked at; the rest get minus infinity.
    """
    block = query_block(queries)
    every = np.concatenate([q for _, q, _ in block]) if block else np.zeros((0, 1))
    size = np.array([len(q) for _, q, _ in block], np.int64)
    first = np.cumsum(size) - size

    def excess(u, met, w):
        out = np.full(len(w), -np.inf)
        bound = 2 * np.sqrt(np.maximum(1 - w, 0) * np.maximum(met.size, len(u)))
        near = np.flatnonzero(bound < 2 + 1e-6)
        if not len(size) or not len(near):
            return out
        known = met.__dict__.setdefault("asked", {})  # scores of objects met before
        score = lambda v: np.add.reduceat((every @ v.T).max(1), first)
        own = score(u)
        for i in near.tolist():
            if i not in known:
                known[i] = score(met.of(i))
            out[i] = (np.abs(own - known[i]) - size * bound[i]).max()
        return out

    return excess


def idf_weights(tokens: DataFrame, word: str = "word") -> DataFrame:
    """(word, df, weight): ln(n/df) scaled to 0..1, so that frequent words weigh little."""
    n = tokens.select("mv_id").distinct().count()
    df = tokens.groupBy(word).agg(F.count_distinct("mv_id").alias("df"))
    return df.withColumn("weight", F.log(F.lit(float(max(n, 1))) / F.col("df")) / F.log(F.lit(float(max(n, 2)))))


def softmax_weights(words: DataFrame) -> DataFrame:
    """``words`` (mv_id, word, weight) with weights that sum to one in every object, by softmax."""
    w = Window.partitionBy("mv_id")
    e = words.withColumn("weight", F.exp(F.col("weight") - F.max("weight").over(w)))
    return e.withColumn("weight", F.col("weight") / F.sum("weight").over(w))


def constant_weights(tokens: DataFrame, value: float = 1.0) -> DataFrame:
    """The same weight for every token, 0 to 1."""
    if not 0 <= value <= 1:
        raise ValueError("token weights lie between 0 and 1")
    return tokens.withColumn("weight", F.lit(float(value)))


def given_weights(tokens: DataFrame, weights: DataFrame) -> DataFrame:
    """Weights supplied by (qid, q_ix, weight); tokens without one weigh 1."""
    return tokens.join(weights.select("qid", "q_ix", "weight"), ["qid", "q_ix"], "left").withColumn("weight", F.coalesce("weight", F.lit(1.0)))
