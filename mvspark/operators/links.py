"""Links from tokens to correlated foreign objects, and their use in a search step, in set form."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..config import IndexConfig, LinkConfig
from ..functions import kernel
from .shards import rows_of, single
from .similarity import QUERY_VALUES, each_query

#: tokens that meet a block of tokens at a time
WIDTH = 32_768


def token_neighbours(tokens: DataFrame, m_prime: int, cells: DataFrame | None = None) -> DataFrame:
    """(mv_id, tok_ix, other_mv, other_tok, s): the m_prime nearest tokens of other objects.

    Without ``cells`` exact: all tokens are held by every task, which the size check allows for small
    data only, and each task keeps m_prime rows a token. With ``cells`` (mv_id, tok_ix, cell) only
    tokens of one cell meet, by an equi-join, which is the form for large data.
    """
    if cells is None:
        n, d = tokens.agg(F.count("*"), F.max(F.size("vec"))).first()
        if (n or 0) * (d or 0) > QUERY_VALUES:
            raise ValueError("too many tokens for the exact form; give cells")
        rows = tokens.select("mv_id", "tok_ix", "vec").orderBy("mv_id", "tok_ix").toArrow()
        ids, ix = rows.column("mv_id").to_numpy(), rows.column("tok_ix").to_numpy()
        vec = rows.column("vec").combine_chunks()
        x = vec.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(ids), -1) if len(ids) else np.zeros((0, 1))

        def nearest(frames):
            for f in frames:
                for at in range(0, len(f), 500):
                    some = f.iloc[at : at + 500]
                    scores = np.array(some["vec"].tolist(), float) @ x.T
                    out = []
                    for own, own_ix, row in zip(some["mv_id"], some["tok_ix"], scores):
                        row[ids == own] = -np.inf
                        k = min(m_prime, int((ids != own).sum()))
                        if not k:
                            continue
                        bar = np.partition(row, len(row) - k)[len(row) - k]
                        top = np.flatnonzero(row >= bar)
                        top = top[np.lexsort((top, -row[top]))][:k]  # rows are in order of id and token
                        out.append(pd.DataFrame({"mv_id": own, "tok_ix": own_ix, "other_mv": ids[top], "other_tok": ix[top], "s": row[top]}))
                    if out:
                        yield pd.concat(out)

        return tokens.select("mv_id", "tok_ix", "vec").mapInPandas(nearest, "mv_id long, tok_ix int, other_mv long, other_tok int, s double")
    from ..functions.vectors import dot

    t = tokens.join(cells, ["mv_id", "tok_ix"])
    a = t.select("cell", F.col("mv_id").alias("own"), F.col("tok_ix").alias("own_ix"), F.col("vec").alias("x"))
    s = a.join(t, "cell").where("own <> mv_id").select("own", "own_ix", "mv_id", "tok_ix", dot(F.col("x"), F.col("vec")).alias("s"))
    w = Window.partitionBy("own", "own_ix").orderBy(F.desc("s"), "mv_id", "tok_ix")
    near = s.withColumn("r", F.row_number().over(w)).where(F.col("r") <= m_prime)
    return near.select(F.col("own").alias("mv_id"), F.col("own_ix").alias("tok_ix"), F.col("mv_id").alias("other_mv"), F.col("tok_ix").alias("other_tok"), "s")


def build_links(tokens: DataFrame, m: int, gamma: int = 1, factor: int = 5, cells: DataFrame | None = None) -> DataFrame:
    """(mv_id, tok_ix, pos, linked_mv, key): per token the m foreign objects of largest top-gamma sum, in order."""
    near = token_neighbours(tokens, factor * m, cells)
    inside = Window.partitionBy("mv_id", "tok_ix", "other_mv").orderBy(F.desc("s"), "other_tok")
    owners = near.withColumn("r", F.row_number().over(inside)).where(F.col("r") <= gamma)
    owners = owners.groupBy("mv_id", "tok_ix", F.col("other_mv").alias("linked_mv")).agg(F.sum("s").alias("key"))
    order = Window.partitionBy("mv_id", "tok_ix").orderBy(F.desc("key"), "linked_mv")
    return owners.withColumn("pos", F.row_number().over(order)).where(F.col("pos") <= m).select("mv_id", "tok_ix", "pos", "linked_mv", "key")


def expansion_set(links: DataFrame) -> DataFrame:
    return links.select("mv_id", "linked_mv").distinct()


def contributions(scores: DataFrame, gamma: int = 1) -> DataFrame:
    """(qid, mv_id, tok_ix, part): what each visited token adds to gamma times the similarity; 0 where nothing."""
    w = Window.partitionBy("qid", "q_ix", "mv_id").orderBy(F.desc("s"), "tok_ix")
    near = scores.withColumn("r", F.row_number().over(w))
    return near.groupBy("qid", "mv_id", "tok_ix").agg(F.sum(F.when(F.col("r") <= gamma, F.col("s")).otherwise(0.0)).alias("part"))


def relevance(parts: DataFrame, scale: float = 1.0) -> DataFrame:
    """Softmax of contributions over the tokens of a visited object."""
    w = Window.partitionBy("qid", "mv_id")
    e = F.exp((F.col("part") - F.max("part").over(w)) / scale)
    return parts.withColumn("e", e).withColumn("rel", F.col("e") / F.sum("e").over(w)).drop("e")


def priorities(rel: DataFrame, links: DataFrame) -> DataFrame:
    """(qid, mv_id, linked_mv, priority): best token relevance times link key."""
    met = rel.join(links, ["mv_id", "tok_ix"])
    return met.groupBy("qid", "mv_id", "linked_mv").agg(F.max(F.col("rel") * F.col("key")).alias("priority"))


def top_links(prio: DataFrame, m: int) -> DataFrame:
    w = Window.partitionBy("qid", "mv_id").orderBy(F.desc("priority"), "linked_mv")
    return prio.withColumn("pos", F.row_number().over(w)).where(F.col("pos") <= m)


def _parts(met: kernel.Block, s: np.ndarray, gamma: int) -> np.ndarray:
    """What each token of a block adds to gamma times its object's similarity; ties by place."""
    out = np.zeros(len(met.x))
    for at, cube in kernel.cubes(s, met.start, met.size):
        pick = cube.argmax(2)[:, :, None] if gamma == 1 else np.argsort(-cube, axis=2, kind="stable")[:, :, :gamma]
        out += np.bincount((met.start[at][None, :, None] + pick).ravel(), np.take_along_axis(cube, pick, 2).ravel(), len(out))
    return out


def _softmax(met: kernel.Block, part: np.ndarray, scale: float) -> np.ndarray:
    """Relevance of every token of a block, by softmax over its object."""
    e = np.exp((part - np.repeat(np.maximum.reduceat(part, met.start), met.size)) / scale)
    return e / np.repeat(np.add.reduceat(e, met.start), met.size)


def token_parts(queries: DataFrame, objs: DataFrame, gamma: int = 1, scale: float | None = None) -> DataFrame:
    """(qid, mv_id, tok_ix, part[, rel]): as ``contributions``, and with ``scale`` ``relevance``, of all token scores, object by object."""

    def work(met, ids, _):
        owner, place = np.repeat(ids, met.size), (np.arange(len(met.x)) - np.repeat(met.start, met.size)).astype(np.int32)

        def one(qid, q, w, s):
            part = _parts(met, s, gamma)
            return [owner, place, part, *([_softmax(met, part, scale)] if scale else [])]

        return one

    return each_query(queries, objs, work, "qid long, mv_id long, tok_ix int, part double" + ", rel double" * bool(scale))


class _Links:
    """The links of a block of objects by (object, linked object), with what they are worth for a query."""

    def __init__(self, met: kernel.Block, column):
        size = np.asarray(column.value_lengths().fill_null(0), np.int64)
        flat = column.flatten()
        tok, linked, key = (flat.field(c).to_numpy(zero_copy_only=False) for c in ("tok_ix", "linked_mv", "key"))
        owner = np.repeat(np.arange(len(size)), size)
        order = np.lexsort((linked, owner))
        owner, self.row, linked, self.key = owner[order], (met.start[owner] + tok)[order], linked[order], key[order]
        lead = np.concatenate([[True], (owner[1:] != owner[:-1]) | (linked[1:] != linked[:-1])]) if len(owner) else np.zeros(0, bool)
        self.first = np.flatnonzero(lead)
        self.owner, self.linked = owner[self.first], linked[self.first]

    def priorities(self, rel: np.ndarray) -> np.ndarray:
        return np.maximum.reduceat(rel[self.row] * self.key, self.first) if len(self.first) else np.zeros(0)

    def best(self, priority: np.ndarray, m: int) -> tuple[np.ndarray, np.ndarray]:
        """(places, ranks) of the m links of highest priority of each object, ties by linked object."""
        order = np.lexsort((self.linked, -priority, self.owner))
        own = self.owner[order]
        pos = np.arange(len(own)) - np.searchsorted(own, own)
        return order[pos < m], (pos[pos < m] + 1).astype(np.int32)


def rounded(x: np.ndarray, digits: int) -> np.ndarray:
    """Half away from zero."""
    return np.sign(x) * np.floor(np.abs(x) * 10.0**digits + 0.5) / 10.0**digits


def link_priorities(queries: DataFrame, objs: DataFrame, links: DataFrame, gamma: int = 1, scale: float = 1.0, m: int | None = None, digits: int | None = None) -> DataFrame:
    """(qid, mv_id, linked_mv, priority[, pos]): as ``priorities``, and with ``m`` ``top_links``, of all queries and objects, object by object."""

    def work(met, ids, more):
        own = _Links(met, more[0])

        def one(qid, q, w, s):
            got = own.priorities(_softmax(met, _parts(met, s, gamma), scale))
            got = got if digits is None else rounded(got, digits)
            if m is None:
                return ids[own.owner], own.linked, got
            at, pos = own.best(got, m)
            return ids[own.owner[at]], own.linked[at], got[at], pos

        return one

    from .graph import nest_links

    return each_query(queries, objs.join(nest_links(links), "mv_id"), work, "qid long, mv_id long, linked_mv long, priority double" + ", pos int" * (m is not None), ("links",))


def unlike_pops(queries: DataFrame, objs: DataFrame, links: DataFrame, m: int, gamma: int = 1, scale: float = 1.0) -> DataFrame:
    """(qid, mv_id, linked_mv): links that only the search's lazy pops or only the full scan of priorities takes, ties at the border aside."""
    from .graph import nest_links, popped

    def work(met, ids, more):
        own = _Links(met, more[0])
        lists = []
        for i, l in enumerate(more[0]):
            mine: dict[int, list] = {}
            for t, to, key in zip(*(l.values.field(c).to_pylist() for c in ("tok_ix", "linked_mv", "key"))):
                mine.setdefault(t, []).append((key, to))
            lists.append(mine)
        edge = np.searchsorted(own.owner, np.arange(len(ids) + 1)).tolist()
        name = own.linked.tolist()

        def one(qid, q, w, s):
            rel = _softmax(met, _parts(met, s, gamma), scale)
            got = own.priorities(rel)
            at, _ = own.best(got, m)
            cut, mv, to = np.searchsorted(own.owner[at], np.arange(len(ids) + 1)).tolist(), [], []
            at, each = at.tolist(), rel.tolist()
            for i, (a, n) in enumerate(zip(met.start.tolist(), met.size.tolist())):
                top = at[cut[i] : cut[i + 1]]
                scan, pops = {name[k] for k in top}, set(popped(each[a : a + n], lists[i], m)[0])
                if scan != pops:
                    least = min((got[k] for k in top), default=np.nan)
                    real = dict(zip(name[edge[i] : edge[i + 1]], got[edge[i] : edge[i + 1]]))
                    for x in scan ^ pops:
                        if not abs(real.get(x, np.nan) - least) <= 1e-9 * abs(least):
                            mv.append(ids[i])
                            to.append(x)
            return np.array(mv, np.int64), np.array(to, np.int64)

        return one

    return each_query(queries, objs.join(nest_links(links), "mv_id"), work, "qid long, mv_id long, linked_mv long", ("links",))


def unsorted_links(links: DataFrame) -> DataFrame:
    """Places where a list's keys rise: none in a sound table."""
    w = Window.partitionBy("mv_id", "tok_ix").orderBy("pos")
    return links.withColumn("last", F.lag("key").over(w)).where("key > last")


# --- links inside shards ---


def _owners(row: np.ndarray, owner: np.ndarray, s: np.ndarray, gamma: int, m: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(row, pos, owner, key): of each row's tokens the m owners of largest top-gamma sum, in order."""
    order = np.lexsort((-s, owner, row))
    row, owner, s = row[order], owner[order], s[order]
    lead = np.concatenate([[True], (row[1:] != row[:-1]) | (owner[1:] != owner[:-1])]) if len(row) else np.zeros(0, bool)
    first = np.flatnonzero(lead)
    nth = np.arange(len(row)) - np.repeat(first, np.diff(np.append(first, len(row))))
    key = np.add.reduceat(np.where(nth < gamma, s, 0), first) if len(first) else np.zeros(0)
    row, owner = row[first], owner[first]
    order = np.lexsort((owner, -key, row))
    row, owner, key = row[order], owner[order], key[order]
    begin = np.flatnonzero(np.concatenate([[True], row[1:] != row[:-1]])) if len(row) else np.zeros(0, np.int64)
    pos = np.arange(len(row)) - np.repeat(begin, np.diff(np.append(begin, len(row))))
    keep = pos < m
    return row[keep], pos[keep] + 1, owner[keep], key[keep]


def _top(s: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, column) of the n largest finite values of every row, ties by column."""
    n = min(n, s.shape[1])
    bar = np.partition(s, s.shape[1] - n, axis=1)[:, s.shape[1] - n]
    row, col = np.nonzero((s >= bar[:, None]) & np.isfinite(s))
    order = np.lexsort((col, -s[row, col], row))
    row, col = row[order], col[order]
    begin = np.searchsorted(row, np.arange(len(s)))
    keep = np.arange(len(row)) - begin[row] < n
    return row[keep], col[keep]


def nearest_exact(x: np.ndarray, owner: np.ndarray, n: int, block: int = 256, width: int = WIDTH):
    """(row, column, s) of every token's n nearest tokens of other owners, ``block`` tokens with ``width`` at a time; owners rise.

    What is kept of a row sets the bar for the columns that follow: equal ones come later and lose, so only larger ones are looked at.
    """
    first = np.searchsorted(owner, owner, side="left")
    last = np.searchsorted(owner, owner, side="right")
    for lo in range(0, len(x), block):
        some = x[lo : lo + block]
        bar = np.full((len(some), 1), -np.inf, np.float32)
        row, col, val = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.float32)
        heads = lo + np.flatnonzero(np.concatenate([[True], owner[lo + 1 : lo + len(some)] != owner[lo : lo + len(some) - 1]]))
        for at in range(0, len(x), width):
            s = some @ x[at : at + width].T
            for h in heads[(first[heads] < at + width) & (last[heads] > at)].tolist():
                s[h - lo : last[h] - lo, max(first[h] - at, 0) : max(last[h] - at, 0)] = -np.inf
            if not len(row):
                r, c = _top(s, n)
            else:
                r, c = np.nonzero(s > bar)
            if not len(r):
                continue
            row, col, val = np.concatenate([row, r]), np.concatenate([col, c + at]), np.concatenate([val, s[r, c]])
            order = np.lexsort((col, -val, row))
            row, col, val = row[order], col[order], val[order]
            nth = np.arange(len(row)) - np.searchsorted(row, row)
            keep = nth < n
            full = nth == n - 1
            bar[row[full], 0] = val[full]
            row, col, val = row[keep], col[keep], val[keep]
        yield row + lo, col, val.astype(np.float64)


def nearest_in_cells(x: np.ndarray, owner: np.ndarray, n: int, probes: int, seed_every: int = 1, block: int = 4096):
    """As ``nearest_exact``, but a token meets only the tokens of the cells of the ``probes`` centres nearest to it."""
    k = max(1, int(np.sqrt(len(x))))
    c = x[np.linspace(0, len(x) - 1, k).astype(int)].copy()
    for _ in range(4):
        own = (x @ c.T - 0.5 * (c**2).sum(1)).argmax(1)
        n_of = np.bincount(own, minlength=k)
        total = np.zeros_like(c)
        np.add.at(total, own, x)
        c = np.where(n_of[:, None] > 0, total / np.maximum(n_of, 1)[:, None], c)
    own = (x @ c.T - 0.5 * (c**2).sum(1)).argmax(1)
    members = np.argsort(own, kind="stable")
    edge = np.searchsorted(own[members], np.arange(k + 1))
    for lo in range(0, len(x), block):
        near = np.argsort(-(x[lo : lo + block] @ c.T), axis=1, kind="stable")[:, :probes]
        rows, cols, vals = [], [], []
        for cell in np.unique(near):
            mine, other = np.flatnonzero((near == cell).any(1)) + lo, members[edge[cell] : edge[cell + 1]]
            if not len(other):
                continue
            s = x[mine] @ x[other].T
            s[owner[mine][:, None] == owner[other][None]] = -np.inf
            r, q = _top(s, n)
            rows.append(mine[r])
            cols.append(other[q])
            vals.append(s[r, q])
        row, col, s = (np.concatenate(v) for v in (rows, cols, vals))
        order = np.lexsort((col, -s, row))
        row, col, s = row[order], col[order], s[order]
        begin = np.searchsorted(row, np.arange(lo, min(lo + block, len(x))))
        keep = np.arange(len(row)) - begin[row - lo] < n
        yield row[keep], col[keep], s[keep].astype(np.float64)


def nearest_by_graph(x: np.ndarray, owner: np.ndarray, n: int, cfg: LinkConfig):
    """As ``nearest_exact``, by searches of an ordinary layered graph over the tokens."""
    from .graph import Shard, levels

    index = IndexConfig(M=16, ef_construction=max(32, cfg.ef))
    g = Shard(index, np.arange(len(x)), x, np.ones(len(x), np.int64)).insert_all(levels(len(x), index))
    rows, cols, vals = [], [], []
    most = int(np.bincount(owner).max(initial=0))
    for i in range(len(x)):
        found = g.nearest(x[i], max(cfg.ef, n + most))
        found = [(v, j) for v, j in found if owner[j] != owner[i]][:n]
        rows += [i] * len(found)
        cols += [j for _, j in found]
        vals += [v for v, _ in found]
    yield np.array(rows, np.int64), np.array(cols, np.int64), np.array(vals)


def shard_links(objs: DataFrame, cfg: LinkConfig) -> DataFrame:
    """(shard, mv_id, tok_ix, pos, linked_mv, key): links between objects of one shard, so that a search of the shard can follow all.

    The nearest tokens come from all tokens of the shard, however many, from cells, or from a token graph. A task holds its shard's tokens
    once, in single precision, and hands on the links of a block of tokens at a time.
    """
    kinds = [("shard", pa.int32()), ("mv_id", pa.int64()), ("tok_ix", pa.int32()), ("pos", pa.int32()), ("linked_mv", pa.int64()), ("key", pa.float64())]

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard, ids, tokens, sizes = 0, [], [], []
        for b in batches:
            if len(b):
                shard = b.column(0)[0].as_py()
                x, size = rows_of(b.column(2))
                ids.append(b.column(1).to_numpy())
                sizes.append(size)
                if len(x):
                    tokens.append(np.array(x, np.float32))
        if not tokens:
            return
        ids, size, x = np.concatenate(ids), np.concatenate(sizes), np.concatenate(tokens)
        tokens.clear()
        order = np.argsort(ids, kind="stable")
        x = x[kernel.spans((np.cumsum(size) - size)[order], size[order])]
        ids, size = ids[order], size[order]
        owner = np.repeat(np.arange(len(ids)), size)
        tok = np.arange(len(owner)) - np.repeat(np.cumsum(size) - size, size)
        n = cfg.factor * cfg.M
        near = {"exact": lambda: nearest_exact(x, owner, n), "cells": lambda: nearest_in_cells(x, owner, n, cfg.probes), "graph": lambda: nearest_by_graph(x, owner, n, cfg)}
        for found, col, s in near[cfg.how]():
            row, pos, own, key = _owners(found, owner[col], s, cfg.gamma, cfg.M)
            cols = [np.full(len(row), shard), ids[owner[row]], tok[row], pos, ids[own], key]
            yield pa.RecordBatch.from_arrays([pa.array(c).cast(k) for c, (_, k) in zip(cols, kinds)], names=[n for n, _ in kinds])

    rows = objs.select("shard", "mv_id", single())
    return rows.groupBy("shard").applyInArrow(build, "shard int, mv_id long, tok_ix int, pos int, linked_mv long, key double")


def link_loss(links: DataFrame, shards: DataFrame) -> DataFrame:
    """(links, lost, share): links of a table that lead to another shard than their object's, by ``shards`` (mv_id, shard)."""
    a = links.select("mv_id", "linked_mv").join(shards.select("mv_id", F.col("shard").alias("own")), "mv_id")
    b = a.join(shards.select(F.col("mv_id").alias("linked_mv"), F.col("shard").alias("other")), "linked_mv")
    lost = F.sum((F.col("own") != F.col("other")).cast("long"))
    return b.agg(F.count("*").alias("links"), F.coalesce(lost, F.lit(0)).alias("lost")).withColumn("share", F.col("lost") / F.greatest(F.col("links"), F.lit(1)))
