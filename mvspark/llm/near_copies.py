"""Near copies of whole texts: SimHash links first, then every pair of five-word Jaccard similarity 0.8 or more.

A text is the set of its five-word shingles (A-Z lower-cased, split at white space), each named by 64 bits.
Texts whose 64-bit SimHash over them differs in two bits at most are found by the generalised pigeonhole search and
linked if their sets are similar. Two bits catch few pairs of similarity 0.8, which differ in some ten, so an exact
prefix join completes the links.
Shingles are ordered from rare to frequent by a sketch of counts; two sets of similarity 0.8 then share one
among the first of both, so only documents that meet there are compared, on their whole sets. The
members of a shingle first meet ``DRAWN`` of them, which costs a few pairs a member however many they are; those
that still lie in different components then meet each other, so no link is lost. Links are contracted to components.
Sets are hashed anew for each pass, as they take more room than the texts.

Defined results: null text and text without words are one text; texts of fewer than five words are one shingle;
rows with one doc_id are one document; null ids are last and, alone in a group, give a null component; an
empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import simhash
from .common import components, text_of, without, written
from .paragraph_dedup import PICKED, prefix_sizes

SHINGLE, SIMILAR = 5, 0.8
#: counters by which shingles are called rare or frequent (an order only, no result depends on it)
SKETCH = 1 << 18
#: members of a shingle that all others meet first, and texts hashed at a time
DRAWN, BATCH = 2, 500
#: words of 64 parities of a text's shingles
PARITY = 8

_ROW = ["key", "n", "at", "short"]


def shingles(text: str) -> tuple[int, np.ndarray]:
    """A 64-bit name of the text's words, and the names of its shingles in order, repeats included."""
    from xxhash import xxh3_64_intdigest

    words = text.encode("utf-8", "surrogatepass").lower().split()
    key = np.array([xxh3_64_intdigest(b" ".join(words))], np.uint64)
    if len(words) < SHINGLE:
        return int(key.view(np.int64)[0]), key
    w = np.array([xxh3_64_intdigest(x) for x in words], np.uint64)
    v = np.zeros(len(w) - SHINGLE + 1, np.uint64)
    for i in range(SHINGLE):
        v = (v ^ w[i : len(v) + i]) * np.uint64(0x9E3779B97F4A7C15)
        v ^= v >> np.uint64(32)
    return int(key.view(np.int64)[0]), v


def fingerprint(v: np.ndarray, block: int = 100_000) -> int:
    """SimHash of shingle names: a bit is set if set in over half of them."""
    ones = np.zeros(64, np.int64)
    for i in range(0, len(v), block):
        raw = (v[i : i + block] * np.uint64(0xD1B54A32D192ED03)).astype(">u8").view(np.uint8).reshape(-1, 8)
        ones += np.unpackbits(raw, axis=1).sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(v)).view(">u8").astype(np.uint64).view(np.int64)[0])


def parities(h: np.ndarray) -> np.ndarray:
    """Words whose bits count shingles modulo two; two sets' differ in no more bits than the sets in members."""
    odd = np.bincount((h >> np.uint64(40)).astype(np.int64) % (64 * PARITY), minlength=64 * PARITY) & 1
    return np.packbits(odd.astype(bool)).view(np.int64)


def _names(batches):
    """Rows (doc_id, check, key, fp, n, odd), and at the end one row of how often each sketch cell was hit."""
    total = np.zeros(SKETCH, np.int64)
    kinds = [pa.int64()] * 5 + [pa.list_(pa.int64())] * 2
    names = ["doc_id", "check", "key", "fp", "n", "odd", "cells"]
    emit = lambda *cols: pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], names=names)
    for b in batches:
        for lo in range(0, b.num_rows, BATCH):
            some = b.slice(lo, BATCH)
            keys, fps, cells, sizes, odd = [], [], [], [], []
            for t in some.column(1).to_pylist():
                key, v = shingles(t)
                h = np.unique(v)
                keys.append(key)
                fps.append(fingerprint(v))
                cells.append(_cells(h.view(np.int64)))
                sizes.append(len(h))
                odd.append(parities(h).tolist())
            total += np.bincount(np.concatenate(cells), minlength=SKETCH)
            yield emit(some.column(0).to_pylist(), some.column(2).to_pylist(), keys, fps, sizes, odd, [None] * some.num_rows)
    yield emit([None], [None], [None], [None], [None], [None], [total.tolist()])


def _sets(batches):
    """(key, h): the name and the sorted shingle names of each text."""
    for b in batches:
        for lo in range(0, b.num_rows, BATCH):
            got = [(k, np.unique(v.view(np.int64))) for k, v in map(shingles, b.column(0).slice(lo, BATCH).to_pylist())]
            ends = np.cumsum([0] + [len(h) for _, h in got]).astype(np.int32)
            flat = pa.array(np.concatenate([h for _, h in got]))
            yield pa.RecordBatch.from_arrays(
                [pa.array([k for k, _ in got], pa.int64()), pa.ListArray.from_arrays(pa.array(ends), flat)], names=["key", "h"]
            )


def _cells(h: np.ndarray) -> np.ndarray:
    return (h & (SKETCH - 1)).astype(np.int64)


def _prefixes(batches, count: np.ndarray):
    """The rarest shingles of each text, as many as a similar set must share one of."""
    for b in batches:
        for lo in range(0, b.num_rows, BATCH):
            first, n, at, short, key = [], [], [], [], []
            for t in b.column(0).slice(lo, BATCH).to_pylist():
                k, v = shingles(t)
                h = np.unique(v.view(np.int64))
                own, wide = prefix_sizes(len(h), SIMILAR)
                first.append(h[np.lexsort((h, count[_cells(h)]))[:wide]])
                n.append(np.full(wide, len(h), np.int32))
                at.append(np.arange(wide, dtype=np.int32))
                short.append(at[-1] < own)
                key.append(np.full(wide, k, np.int64))
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in (first, key, n, at, short)], names=["shingle", *_ROW])


def _verify(batches):
    for b in batches:
        keep = []
        for i in range(b.num_rows):
            x, y = (b.column(c)[i].values.to_numpy() for c in (2, 3))
            both = len(np.intersect1d(x, y, assume_unique=True))
            keep.append(both >= SIMILAR * (len(x) + len(y) - both) - 1e-9)
        yield pa.RecordBatch.from_arrays([b.column(0), b.column(1)], names=["a", "b"]).filter(pa.array(keep, pa.bool_()))


def _fits() -> Column:
    """Rows x and y of one shingle, if it is the first that their sets share, leave room for enough others."""
    both = (F.col("x.n") + F.col("y.n")) * F.lit(SIMILAR / (1 + SIMILAR)) - F.lit(1e-9)
    room = F.least(F.col("x.n") - F.col("x.at"), F.col("y.n") - F.col("y.at")) >= both
    return room & F.expr("x.key <> y.key and (x.short and x.n <= y.n or y.short and y.n <= x.n)")


def _near(x: Column, y: Column) -> Column:
    """Two sets (n, odd) may be similar: their sizes fit, and their parities differ in no more bits than similar sets' members."""
    both = F.ceil((x["n"] + y["n"]) * F.lit(SIMILAR / (1 + SIMILAR)) - F.lit(1e-9))
    bits = sum((F.bit_count(x["odd"][i].bitwiseXOR(y["odd"][i])) for i in range(PARITY)), F.lit(0))
    return (F.least(x["n"], y["n"]) >= both) & (bits <= x["n"] + y["n"] - 2 * both)


def _verified(pairs: DataFrame, texts: DataFrame, named: DataFrame, label: str) -> DataFrame:
    """Of the pairs (a, b) of names those whose whole sets are similar. Only the texts they name are hashed, one for each name."""
    seen = named.groupBy("key").agg(F.first("n").alias("n"), F.first("odd").alias("odd"))
    a, b = (seen.select(F.col("key").alias(c), F.struct("n", "odd").alias(f"of_{c}")) for c in "ab")
    pairs = pairs.where("a <> b").distinct().join(a, "a").join(b, "b").where(_near(F.col("of_a"), F.col("of_b"))).select("a", "b")
    pairs = written(pairs, f"{label}-pairs")
    needed = pairs.select(F.col("a").alias("key")).union(pairs.select(F.col("b").alias("key"))).distinct()
    needed = written(named.join(needed, "key").groupBy("key").agg(F.min("check").alias("check")), f"{label}-needed")
    pick = needed.select("check").distinct()
    some = texts.join(F.broadcast(pick) if needed.count() <= PICKED else pick, "check", "left_semi").select("text")
    bodies = written(some.mapInArrow(_sets, "key long, h array<long>").dropDuplicates(["key"]), f"{label}-sets", "uncompressed")
    both = pairs.join(bodies.select(F.col("key").alias("a"), F.col("h").alias("x")), "a")
    both = both.join(bodies.select(F.col("key").alias("b"), F.col("h").alias("y")), "b").select("a", "b", "x", "y")
    return written(both.mapInArrow(_verify, "a long, b long"), f"{label}-links")


def _met(rows: DataFrame) -> DataFrame:
    """Pairs (a, b) of the rows (x, y) of one shingle that can be similar."""
    return rows.where(_fits()).select(F.least("x.key", "y.key").alias("a"), F.greatest("x.key", "y.key").alias("b"))


def by_fingerprint(texts: DataFrame, named: DataFrame) -> DataFrame:
    """Links (a, b) between names of texts whose fingerprints differ in two bits at most, as far as their sets are similar."""
    each = written(named.groupBy("fp").agg(F.min("key").alias("key"), F.count_distinct("key").alias("n")), "fingerprints")
    same = named.join(each.where("n > 1").select("fp", F.col("key").alias("a")), "fp").select("a", F.col("key").alias("b"))
    ends = simhash.links(each.select("fp", F.lit(0).alias("low")))
    near = ends.join(each.select(F.col("fp").alias("a"), F.col("key").alias("x")), "a").join(each.select(F.col("fp").alias("b"), F.col("key").alias("y")), "b")
    near = near.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))
    return _verified(same.unionByName(near), texts, named, "fingerprint")


def links(texts: DataFrame, named: DataFrame, drawn: int = DRAWN) -> DataFrame:
    """Edges (a, b) between names of texts that connect all pairs of similarity ``SIMILAR``.

    ``texts`` has (text, check), ``named`` the rows of ``_names``.
    """
    cells = named.where("cells is not null").select(F.posexplode("cells").alias("cell", "n")).where("n > 0")
    got = cells.groupBy("cell").agg(F.sum("n").alias("n")).toPandas()  # SKETCH rows at most
    count = np.zeros(SKETCH, np.int32)
    count[got["cell"].to_numpy(np.int64)] = np.minimum(got["n"].to_numpy(np.int64), 2**31 - 1)
    named = named.where("key is not null")
    first = by_fingerprint(texts, named)
    rows = texts.select("text").mapInArrow(lambda it: _prefixes(it, count), "shingle long, key long, n int, at int, short boolean")
    by = Window.partitionBy("shingle").orderBy("key")
    rows = rows.withColumn("low", F.lag("key").over(by)).withColumn("high", F.lead("key").over(by)).where("low < key or high > key")
    rows = written(rows.select("shingle", *_ROW).distinct(), "shared")
    row = F.struct(*_ROW)
    turn = [F.min_by(row, F.struct(F.xxhash64(F.lit(i), "shingle", "key"), F.col("key"))) for i in range(drawn)]
    reps = rows.groupBy("shingle").agg(F.count("*").alias("members"), F.array_distinct(F.array(*turn)).alias("reps"))
    reps = written(reps, "drawn")
    met = rows.join(reps.select("shingle", "reps"), "shingle").select(row.alias("x"), F.explode("reps").alias("y"))
    near = first.unionByName(_verified(_met(met), texts, named, "drawn"))
    # members still apart: those of the component with most rows need not meet each other
    roots = components(near, "near").select(F.col("v").alias("key"), "root")
    more = rows.join(reps.where("members > 2").select("shingle"), "shingle", "left_semi").join(roots, "key", "left")
    odd = named.groupBy("key").agg(F.first("odd").alias("odd"))
    row = F.struct(*_ROW, "odd")
    more = written(more.join(odd, "key").select("shingle", row.alias("row"), F.coalesce("root", "key").alias("comp")), "apart")
    tally = more.groupBy("shingle", "comp").agg(F.count("*").alias("rows")).groupBy("shingle")
    tally = tally.agg(F.max_by("comp", F.struct("rows", "comp")).alias("main"), F.count("*").alias("comps")).where("comps > 1")
    x = more.join(tally, "shingle").where("comp <> main").select("shingle", F.col("row").alias("x"), F.col("comp").alias("one"))
    y = more.select("shingle", F.col("row").alias("y"), F.col("comp").alias("two"))
    return near.unionByName(_verified(_met(x.join(y, "shingle").where("one <> two").where(_near(F.col("x"), F.col("y"))).select("x", "y")), texts, named, "apart"))


def near_copies(docs: DataFrame, drawn: int = DRAWN) -> DataFrame:
    """One row per row of ``docs``: doc_id, component_id, and a hash that tells texts of one doc_id apart."""
    text = text_of(docs)
    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), text.alias("text"), F.xxhash64(text).alias("check"))
    named = written(rows.mapInArrow(_names, "doc_id long, check long, key long, fp long, n long, odd array<long>, cells array<long>"), "named")
    roots = components(links(rows.select("text", "check"), named, drawn), "copies")
    named = named.where("key is not null").select("doc_id", "check", "key")
    names = named.groupBy("key").agg(F.min("doc_id").alias("low"))
    names = written(names.join(roots, F.col("key") == F.col("v"), "left").select("key", "low", F.coalesce("root", "key").alias("root")), "names")
    lowest = names.groupBy("root").agg(F.min("low").alias("component_id"))
    label = names.join(lowest, "root").select("key", "component_id")
    return named.join(label, "key").select("doc_id", "component_id", "check")


def drop_near_copies(docs: DataFrame) -> DataFrame:
    """One document of each component, that of the smallest doc_id, with its columns."""
    return without(docs, near_copies(docs).where("not (doc_id <=> component_id)"))
