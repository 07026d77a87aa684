"""Passages that repeat across documents: paragraph MinHash banding with exact verification.

A paragraph is a line of at least ``SHINGLE`` words (A-Z lower-cased, split at white space). Bands of
MinHash values over five-word shingles are tuned so that paragraphs of Jaccard similarity 0.8 collide
with probability over 0.99. Equal paragraphs are one vertex. In each band's bucket, members meet
each other when they are few, and else several representatives drawn anew for every band, so a large
bucket costs a few pairs a member. Pairs are verified by exact Jaccard and clustered by components.
Large buckets whose members then still lie in different components go through a prefix filter: of two sets of
similarity 0.8 the rarest shingles of one meet those of the other, so only paragraphs of different components
that share one are verified, and no link within a bucket is lost. In a cluster the
first paragraph (smallest doc_id, then place) stays and the others are removals.

Passages set inside longer lines, or broken into lines otherwise, are found by anchors: runs of ``ANCHOR`` words of the
whole text, picked where their hash is the least among ``WINDOW`` neighbours. Equal runs of ``ANCHOR + WINDOW - 1`` = 50
words or more have an anchor in common, wherever they lie, and an anchor in common is an equal run of 24 words.

Defined results: null and empty texts have no paragraphs; a document repeated under one doc_id does not
repeat across documents; null ids are ignored; an empty table gives an empty result; other columns
are ignored.
"""

from __future__ import annotations

import math
import re

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import components, spread_join, text_of, written
from .lm_score import Texts, _powers, text_batches

SHINGLE, SIMILAR = 5, 0.8
FEW, DRAWN = 12, 4
#: counters by which shingles are called rare or frequent (an order only, no result depends on it)
SKETCH = 1 << 18
#: words of 64 parities of a paragraph's shingles
PARITY = 4
_SIDE = ["key", "comp", "n", "at", "short", *(f"odd{i}" for i in range(PARITY))]
#: words of an anchor, and neighbours of which the least is one; words from which a repeated line is a long passage
ANCHOR, WINDOW, LONG = 24, 27, 50
#: keys at most that are broadcast to pick the lines to verify; more are joined by shuffle
PICKED = 1_000_000


def tuned(similar: float = SIMILAR, recall: float = 0.99, most: int = 64) -> tuple[int, int]:
    """(bands, rows): most rows a band, so fewest candidates, with the wanted recall at ``similar`` within ``most`` values."""
    best = (most, 1)
    for rows in range(1, 9):
        bands = next((b for b in range(1, most // rows + 1) if 1 - (1 - similar**rows) ** b >= recall), None)
        if bands:
            best = (bands, rows)
    return best


def run_names(name: np.ndarray, n: int) -> np.ndarray:
    """Names of all runs of n words, from the words' names."""
    up, down = _powers(len(name) + 1)
    with np.errstate(over="ignore"):
        sums = np.concatenate([[np.uint64(0)], np.cumsum(name * up[: len(name)])])
        h = (sums[n:] - sums[: len(sums) - n]) * down[: max(0, len(name) - n + 1)]
        h = (h ^ (h >> np.uint64(32))) * np.uint64(0x9E3779B97F4A7C15)
        return h ^ (h >> np.uint64(29))


def _slide(x: np.ndarray, n: int, pick) -> np.ndarray:
    """``pick`` (minimum or maximum) of every n neighbours, from each place on."""
    have = 1
    while 2 * have <= n:
        x = pick(x[: len(x) - have], x[have:])
        have *= 2
    return pick(x[: len(x) - (n - have)], x[n - have :]) if n > have else x


def anchors(name: np.ndarray, text: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(first word, name) of the anchors of texts, given as words' names and the text each lies in."""
    if len(name) < ANCHOR + WINDOW - 1:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    h = run_names(name, ANCHOR)
    least = _slide(h, WINDOW, np.minimum)
    span = ANCHOR + WINDOW - 1
    inside = text[: len(least)] == text[span - 1 :]
    least = np.where(inside, least, 0)
    pad = np.zeros(WINDOW - 1, np.uint64)
    most = _slide(np.concatenate([pad, least, pad]), WINDOW, np.maximum)  # of all windows that hold a place
    at = np.flatnonzero((most == h) & (h > 0))
    return at, h[at]


def _units(batches, bands: int, rows: int):
    rng = np.random.default_rng(11)
    mul = rng.integers(1, 1 << 63, bands * rows, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    add = rng.integers(0, 1 << 63, bands * rows, dtype=np.uint64)
    for b in batches:
        ids = b.column(0).to_numpy()
        for at, t in text_batches(b.column(1)):
            doc, text = ids[at], t.text[~t.is_end]
            breaks = np.concatenate([[0], np.cumsum(t.flat == 10)])
            line = breaks[t.start]
            lead = np.flatnonzero(np.concatenate([[True], (line[1:] != line[:-1]) | (text[1:] != text[:-1])])) if len(line) else np.zeros(0, np.int64)
            size = np.diff(np.append(lead, len(line)))
            lead, size = lead[size >= SHINGLE], size[size >= SHINGLE]
            m = len(lead)
            where = text[lead] if m else np.zeros(0, np.int32)
            starts = t.first - np.arange(len(t.first))  # words before each text
            tight = np.concatenate([(t.start[1:] == t.stop[:-1] + 1) & (t.flat[np.minimum(t.stop[:-1], len(t.flat) - 1)] == 32), [False]]) if len(line) else np.zeros(0, bool)
            loose = np.concatenate([[0], np.cumsum(~tight)])
            keys = []
            for i, n, bad in zip(lead.tolist(), size.tolist(), (loose[lead + size - 1] - loose[lead]).tolist() if m else ()):
                if bad:  # white space but one space somewhere
                    raw = b" ".join(t.flat[x:y].tobytes() for x, y in zip(t.start[i : i + n].tolist(), t.stop[i : i + n].tolist()))
                else:
                    raw = t.flat[t.start[i] : t.stop[i + n - 1]].tobytes()
                keys.append(_key(raw))
            sig = np.empty((bands, m), np.uint64)
            if m:
                per = size - SHINGLE + 1
                first = np.cumsum(per) - per
                h = run_names(t.name, SHINGLE)[np.repeat(lead - first, per) + np.arange(int(per.sum()))]
                with np.errstate(over="ignore"):
                    for band in range(bands):
                        v = np.zeros(m, np.uint64)
                        for r in range(band * rows, band * rows + rows):
                            v = (v ^ np.minimum.reduceat(h * mul[r] + add[r], first)) * np.uint64(0x9E3779B97F4A7C15)
                            v ^= v >> np.uint64(32)
                        sig[band] = v
            spot, names = anchors(t.name, text)
            k = len(spot)
            flat = pa.array((sig.T.reshape(-1) >> np.uint64(32)).astype(np.uint32).view(np.int32))
            lists = pa.ListArray.from_arrays(pa.array(np.arange(m + 1, dtype=np.int32) * bands), flat)
            none = pa.nulls(k, pa.list_(pa.int32()))
            before = breaks[t.flat_start]  # line breaks before each text
            both = lambda x, y, kind: pa.array(np.concatenate([x, y]).astype(kind))
            own = text[spot] if k else np.zeros(0, np.int32)
            yield pa.RecordBatch.from_arrays(
                [both(doc[where], doc[own], np.int64), both(line[lead] - before[where] if m else where, np.full(k, -1), np.int32),
                 both(lead - starts[where], spot - starts[own], np.int32), both(size, np.full(k, ANCHOR), np.int64),
                 both(np.array(keys, np.int64), names.view(np.int64), np.int64), pa.concat_arrays([lists, none])],
                names=["doc_id", "place", "start", "n_words", "key", "bands"],
            )


def _key(line: bytes) -> int:
    """A 64-bit name of a text."""
    from xxhash import xxh3_64_intdigest

    k = xxh3_64_intdigest(line)
    return k - (1 << 64) if k >> 63 else k


def _lines(batches):
    for b in batches:
        for lo in range(0, b.num_rows, 400):
            found = {}
            for t in b.slice(lo, 400).column(0).to_pylist():
                for raw in t.encode("utf-8", "surrogatepass").lower().split(b"\n"):
                    w = raw.split()
                    if len(w) >= SHINGLE:
                        line = b" ".join(w)
                        found[_key(line)] = line
            yield pa.RecordBatch.from_arrays([pa.array(list(found), pa.int64()), pa.array(list(found.values()), pa.binary())], names=["key", "line"])


def _verify(batches):
    for b in batches:
        keep = []
        for x, y in zip(b.column(2).to_pylist(), b.column(3).to_pylist()):
            s, t = (_shingles(z) for z in (x, y))
            both = len(s & t)
            keep.append(both >= SIMILAR * (len(s) + len(t) - both))
        yield pa.RecordBatch.from_arrays([b.column(0), b.column(1)], names=["a", "b"]).filter(pa.array(keep, pa.bool_()))


def _shingles(line: bytes) -> set:
    w = line.split(b" ")
    return set(zip(*(w[i:] for i in range(SHINGLE))))


def _hashes(line: bytes) -> np.ndarray:
    from xxhash import xxh3_64_intdigest

    return np.array([xxh3_64_intdigest(b" ".join(x)) for x in _shingles(line)], np.uint64)


def _counts(batches):
    total = np.zeros(SKETCH, np.int64)
    for b in batches:
        for line in b.column(0).to_pylist():
            total += np.bincount((_hashes(line) % np.uint64(SKETCH)).astype(np.int64), minlength=SKETCH)
    cell = np.flatnonzero(total)
    yield pa.RecordBatch.from_arrays([pa.array(cell.astype(np.int32)), pa.array(total[cell])], names=["cell", "n"])


def prefix_sizes(n: int, similar: float = SIMILAR) -> tuple[int, int]:
    """How many of n ordered shingles must be looked at against sets as large or larger, and against smaller ones."""
    return n - math.ceil(2 * similar / (1 + similar) * n - 1e-9) + 1, n - math.ceil(similar * n - 1e-9) + 1


def parities(h: np.ndarray) -> np.ndarray:
    """PARITY words whose bits count shingles modulo two; two sets' differ in no more bits than the sets in members."""
    out = np.zeros(64 * PARITY, np.int64)
    np.add.at(out, (h >> np.uint64(40)).astype(np.int64) % (64 * PARITY), 1)
    return np.packbits((out & 1).astype(bool)).view(np.int64)


def _prefixes(batches, count: np.ndarray):
    for b in batches:
        for lo in range(0, b.num_rows, 2000):
            part = b.slice(lo, 2000)
            shingle, key, comp, n, at, short, odd = [], [], [], [], [], [], []
            for k, c, line in zip(*(part.column(i).to_pylist() for i in range(3))):
                h = _hashes(line)
                own, wide = prefix_sizes(len(h))
                rare = np.lexsort((h, count[(h % np.uint64(SKETCH)).astype(np.int64)]))[:wide]
                shingle.append(h[rare].view(np.int64))
                key += [k] * wide
                comp += [c] * wide
                n += [len(h)] * wide
                at += range(wide)
                odd.append(np.repeat(parities(h)[None], wide, axis=0))
                short += [True] * own + [False] * (wide - own)
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.concatenate(shingle)), pa.array(key, pa.int64()), pa.array(comp, pa.int64()), pa.array(n, pa.int32()),
                 pa.array(at, pa.int32()), pa.array(short, pa.bool_()), *(pa.array(np.ascontiguousarray(c)) for c in np.concatenate(odd).T)],
                names=["shingle", *_SIDE],
            )


def candidates(lines: DataFrame, few: int = FEW, drawn: int = DRAWN) -> tuple[DataFrame, DataFrame]:
    """Distinct pairs (a, b) of keys to verify, from ``lines`` (key, bands), one row a key; and the large buckets' rows."""
    rows = lines.select("key", F.posexplode("bands").alias("band", "value"))
    full = rows.groupBy("band", "value").agg(F.count("*").alias("n")).where("n > 1")
    met = written(rows.join(full, ["band", "value"]), "buckets")
    small = met.where(F.col("n") <= few).groupBy("band", "value").agg(F.array_sort(F.collect_list("key")).alias("m"))
    pairs = F.flatten(F.transform("m", lambda x, i: F.transform(F.slice("m", i + 2, few), lambda y: F.struct(x.alias("a"), y.alias("b")))))
    small = small.select(F.explode(pairs).alias("p")).select("p.a", "p.b")
    crowd = met.where(F.col("n") > few)
    turn = [F.hash(F.lit(i), F.col("band")).cast("long") * F.lit(1 << 31) + F.hash(F.lit(i + 99), F.col("band")) for i in range(drawn)]
    mixed = [F.col("key").bitwiseXOR(t) for t in turn]  # the least key under another order for every band and draw
    reps = crowd.groupBy("band", "value").agg(*(F.min(m).alias(f"r{i}") for i, m in enumerate(mixed)))
    large = crowd.join(reps, ["band", "value"])
    large = large.select("key", F.explode(F.array(*(F.col(f"r{i}").bitwiseXOR(t) for i, t in enumerate(turn)))).alias("r"))
    large = large.where("key <> r").select(F.least("key", "r").alias("a"), F.greatest("key", "r").alias("b"))
    return small.unionByName(large).distinct(), crowd


def _sides(pairs: DataFrame, bodies: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """The verified of ``pairs`` of keys a and b, named by the columns ``a`` and ``b``."""
    met = pairs.join(bodies.select(F.col("key").alias("a"), F.col("line").alias("x")), "a")
    met = met.join(bodies.select(F.col("key").alias("b"), F.col("line").alias("y")), "b")
    return met.select(F.col(a).alias("a"), F.col(b).alias("b"), "x", "y").mapInArrow(_verify, "a long, b long")


def left_over(crowd: DataFrame, bodies: DataFrame, roots: DataFrame) -> DataFrame:
    """Links (a, b) between the components ``roots`` of paragraphs that share a large bucket, all of them."""
    of = crowd.join(roots.select(F.col("v").alias("key"), "root"), "key", "left").withColumn("comp", F.coalesce("root", "key"))
    split = of.groupBy("band", "value").agg(F.min("comp").alias("low"), F.max("comp").alias("high")).where("low <> high")
    keys = written(of.join(split, ["band", "value"], "left_semi").select("key", "comp").distinct(), "open")
    lines = written(keys.join(bodies, "key").select("key", "comp", "line"), "open-lines")
    got = lines.select("line").mapInArrow(_counts, "cell int, n long").groupBy("cell").agg(F.sum("n").alias("n")).toPandas()  # SKETCH rows at most
    count = np.zeros(SKETCH, np.int64)
    count[got["cell"].to_numpy(np.int64)] = got["n"].to_numpy(np.int64)
    schema = "shingle long, key long, comp long, n int, at int, short boolean, " + ", ".join(f"odd{i} long" for i in range(PARITY))
    rows = written(lines.mapInArrow(lambda it: _prefixes(it, count), schema), "prefixes")
    tally = rows.groupBy("shingle", "comp").agg(F.count("*").alias("rows"))
    tally = tally.groupBy("shingle").agg(F.max_by("comp", F.struct("rows", "comp")).alias("main"), F.count("*").alias("comps"))
    rows = rows.join(tally.where("comps > 1").select("shingle", "main"), "shingle")
    x = rows.where("comp <> main").select("shingle", *(F.col(c).alias(f"{c}_x") for c in _SIDE))
    y = rows.select("shingle", *(F.col(c).alias(f"{c}_y") for c in _SIDE))
    both = (F.col("n_x") + F.col("n_y")) * F.lit(SIMILAR / (1 + SIMILAR)) - F.lit(1e-9)  # shingles in common, at least
    first = F.least(F.col("n_x") - F.col("at_x"), F.col("n_y") - F.col("at_y")) >= both  # so for the first that they share
    odd = sum((F.bit_count(F.col(f"odd{i}_x").bitwiseXOR(F.col(f"odd{i}_y"))) for i in range(PARITY)), F.lit(0))
    fits = F.expr("comp_x <> comp_y and (short_x and n_x <= n_y or short_y and n_y <= n_x)")
    met = x.join(y, "shingle").where(fits & first & (odd <= F.col("n_x") + F.col("n_y") - 2 * both))
    end = F.sort_array(F.array(*(F.struct(F.col(f"key_{s}").alias("key"), F.col(f"comp_{s}").alias("comp")) for s in "xy"))).alias("e")
    met = met.select(end).select(*(F.col("e")[i][f].alias(n) for i, f, n in ((0, "key", "a"), (1, "key", "b"), (0, "comp", "one"), (1, "comp", "two"))))
    return _sides(written(met.distinct(), "left-pairs"), bodies, "one", "two")


def repeated_passages(docs: DataFrame, recall: float = 0.99) -> DataFrame:
    """One row per removed or kept passage that repeats: doc_id, place, start, n_words, class_id, keep_id, removed.

    ``place`` is the line number, or -1 for an anchor, ``start`` the first word; ``keep_id`` is the document that keeps it.
    """
    bands, rows = tuned(SIMILAR, recall)
    named = docs.select(docs["doc_id"].cast("long").alias("doc_id"), text_of(docs).alias("text")).where("doc_id is not null")
    units = written(
        named.mapInArrow(lambda it: _units(it, bands, rows), "doc_id long, place int, start int, n_words long, key long, bands array<int>"), "units"
    )
    lines = units.where("place >= 0")
    distinct = written(lines.groupBy("key").agg(F.first("bands").alias("bands"), F.count("*").alias("n")), "paragraphs")
    pairs, crowd = candidates(distinct.select("key", "bands"))
    pairs = written(pairs, "pairs")
    needed = written(pairs.select(F.col("a").alias("key")).union(pairs.select(F.col("b").alias("key"))).distinct(), "needed")
    pick = F.broadcast(needed) if needed.count() <= PICKED else needed
    every = docs.select(text_of(docs).alias("text")).mapInArrow(_lines, "key long, line binary")
    bodies = written(every.join(pick, "key", "left_semi").dropDuplicates(["key"]), "bodies")
    roots = components(_sides(pairs, bodies), "passages")
    more = components(left_over(crowd, bodies, roots), "left").select(F.col("v").alias("w"), F.col("root").alias("to"))
    moved = roots.join(more, F.col("root") == F.col("w"), "left").select("v", F.coalesce("to", "root").alias("root"))
    alone = more.select(F.col("w").alias("v"), F.col("to").alias("root")).join(roots, "v", "left_anti")
    roots = moved.unionByName(alone).select(F.col("v").alias("key"), "root")
    # classes of distinct lines first, so that no line of many documents is joined row by row
    of = distinct.select("key", "n").join(roots, "key", "left").select("key", "n", F.coalesce("root", "key").alias("class"))
    of = written(of, "classes")
    tagged = spread_join(lines.select("key", "doc_id", "place", "start", "n_words"), of, ["key"], "n").select("doc_id", "place", "start", "n_words", "class")
    runs = units.where("place < 0").select("doc_id", "place", "start", "n_words", F.col("key").alias("class"))
    out = None
    for label, part in (("lines", written(tagged, "tagged")), ("runs", runs)):
        spread = part.groupBy("class").agg(
            F.min("doc_id").alias("first"), F.max("doc_id").alias("last"), F.min(F.struct("doc_id", "place", "start")).alias("keep"), F.count("*").alias("rows")
        )
        spread = written(spread.where("first <> last").select("class", "keep", "rows"), f"spread-{label}")
        one = spread_join(part, spread, ["class"], "rows")
        one = one.select(
            "doc_id", "place", "start", "n_words", F.lower(F.hex("class")).alias("class_id"), F.col("keep.doc_id").alias("keep_id"),
            (F.struct("doc_id", "place", "start") != F.col("keep")).alias("removed"),
        )
        out = one if out is None else out.unionByName(one)
    return out


def repeated_documents(docs: DataFrame, recall: float = 0.99) -> DataFrame:
    """One row per document (null ids left out): its class, whether it shares a long passage, counts, and who keeps its passages.

    A long passage is a repeated line of ``LONG`` words or a run of ``ANCHOR`` equal words. ``class_id`` is the smallest doc_id
    that keeps one of the document's long passages, or its own.
    """
    p = written(repeated_passages(docs, recall), "found")
    line = F.col("place") >= 0
    wide = (~line) | (F.col("n_words") >= LONG)
    before = F.lag("start").over(Window.partitionBy("doc_id", line).orderBy("start"))
    p = p.withColumn("fresh", F.when(~line, F.least(F.lit(ANCHOR), F.col("start") - F.coalesce(before, F.lit(-ANCHOR)))))
    one = p.groupBy("doc_id").agg(
        F.min(F.when(wide, F.col("keep_id"))).alias("class_id"), F.max(wide).alias("long_passage"),
        F.count(F.when(line, 1)).alias("n_paragraphs"), F.count(F.when(line & F.col("removed"), 1)).alias("n_removed"),
        F.sum(F.when(line & F.col("removed"), F.col("n_words")).otherwise(0)).alias("words_removed"),
        F.count(F.when(~line, 1)).alias("n_chunks"), F.coalesce(F.sum("fresh"), F.lit(0)).cast("long").alias("chunk_words"),
        F.max("n_words").alias("longest"), F.array_sort(F.collect_set("keep_id")).alias("keep_ids"),
    )
    ids = docs.select(docs["doc_id"].cast("long").alias("doc_id")).where("doc_id is not null").distinct()
    zero = [F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("n_paragraphs", "n_removed", "words_removed", "n_chunks", "chunk_words", "longest")]
    none = F.array().cast("array<long>")
    return ids.join(one, "doc_id", "left").select(
        "doc_id", F.coalesce("class_id", "doc_id").alias("class_id"), F.coalesce("long_passage", F.lit(False)).alias("long_passage"), *zero,
        F.coalesce("keep_ids", none).alias("keep_ids"),
    )


def remove_repeated(docs: DataFrame, recall: float = 0.99) -> DataFrame:
    """``docs`` with the removed paragraphs and the removed runs of words cut from their texts; documents and other columns stay.

    Runs that follow each other closely (as the anchors of one passage do) are cut as one.
    """
    gone = repeated_passages(docs, recall).where("removed").groupBy(F.col("doc_id").alias("id")).agg(
        F.array_sort(F.collect_set(F.when(F.col("place") >= 0, F.col("place")))).alias("lines"),
        F.array_sort(F.collect_set(F.when(F.col("place") < 0, F.col("start")))).alias("runs"),
    )
    rows = docs.select(F.struct(*(docs[c] for c in docs.columns)).alias("row"), docs["doc_id"].cast("long").alias("own"), docs["text"].alias("body"))
    met = rows.join(gone, rows["own"] == gone["id"], "left")
    text = F.when(F.col("id").isNull(), F.col("body")).otherwise(_cut(F.col("body"), F.col("lines"), F.col("runs")))
    return met.select(*(text.alias(c) if c == "text" else F.col("row").getField(c).alias(c) for c in docs.columns))


def without_runs(text: str | None, lines, runs) -> str | None:
    """A text without the given lines and without the runs of words that start at the given words."""
    if text is None:
        return None
    raw = text.encode("utf-8", "surrogatepass")
    words = [m.span() for m in _WORD.finditer(raw)]
    drop = bytearray(len(raw))
    last = -ANCHOR
    for r in runs if runs is not None else ():
        lo = words[min(last + ANCHOR, r)][0] if 0 <= last and r - last <= WINDOW else words[r][0]
        hi = words[r + ANCHOR - 1][1]
        drop[lo:hi] = b"\1" * (hi - lo)
        last = r
    at = 0
    for k, one in enumerate(raw.split(b"\n")):
        if lines is not None and k in set(lines):
            end = min(len(raw), at + len(one) + 1)
            drop[at:end] = b"\1" * (end - at)
        at += len(one) + 1
    return bytes(c for c, d in zip(raw, drop) if not d).decode("utf-8", "surrogatepass")


_WORD = re.compile(rb"[^\x20\x09-\x0D]+")


def _cut(text, lines, runs):
    def run(texts: pd.Series, gone: pd.Series, spans: pd.Series) -> pd.Series:
        return pd.Series([t if g is None else without_runs(t, g, s) for t, g, s in zip(texts, gone, spans)], dtype=object)

    run.__annotations__ = {"texts": pd.Series, "gone": pd.Series, "spans": pd.Series, "return": pd.Series}
    return F.pandas_udf(run, "string")(text, lines, runs)
