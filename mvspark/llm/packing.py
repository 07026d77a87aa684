"""Packing token sequences into as few fixed-size sequences as possible.

Texts are encoded once and cut into pieces, kept in a written table. The plan needs only how many
pieces there are of each length, at most ``size`` numbers whatever the input: best fit by falling length
gives a first packing, held as groups (pattern of lengths, how many bins). Local search then
works on the underfull bins: it moves a piece, exchanges one for one or two for one (either way)
whenever that raises the sum of squared fills, so the emptiest bins drain until they vanish. It ends where
bins cannot be fewer or no two bins hold an exchange: each pair of patterns is looked at once while both
exist. Pieces find their places by their rank within their length.

Defined results: null or empty text is its end id alone; an empty table gives an empty result;
repeated rows are packed as often as they occur; a null doc_id stays null; other columns are
ignored.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections import Counter, defaultdict

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import text_of, written
from .tokenise import default_path, encoder

SIZE = 1024
END = 2
#: words whose ids a worker keeps, about 200 bytes each
CACHE = 1_000_000

_PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, ids binary, part int, nth long"
_KIND = pa.schema([
    ("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()),
    ("ids_crc32", pa.int64()), ("ids", pa.binary()), ("part", pa.int32()), ("nth", pa.int64()),
])


def pieces(docs: DataFrame, size: int = SIZE, end: int = END, tokenizer: str | None = None) -> DataFrame:
    """One row per piece with its ids (little-endian, 2 or 4 bytes an id by vocabulary); ``nth`` counts equal lengths in ``part``."""
    path = tokenizer or default_path()

    def cut(batches):
        enc, seen, part = encoder(path, CACHE), defaultdict(int), TaskContext.get().partitionId()
        tail = np.array([end], enc.kind).tobytes()
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                some = batch.slice(at, 1000)
                cols: list[list] = [[] for _ in range(8)]
                for doc, raw in zip(some.column(0).to_pylist(), enc.ids(some.column(1).to_pylist())):
                    raw += tail
                    n = len(raw) // enc.width
                    lo, k = 0, 0
                    while lo < n:
                        hi = lo + ((n - 1) % size + 1 if k == 0 else size)
                        ids = raw[lo * enc.width : hi * enc.width]
                        wide = np.frombuffer(ids, enc.kind).astype("<u4").tobytes()
                        row = (doc, k, lo, hi - lo, zlib.crc32(wide), ids, part, seen[hi - lo])
                        for c, v in zip(cols, row):
                            c.append(v)
                        seen[hi - lo] += 1
                        lo, k = hi, k + 1
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(cols, _KIND)], schema=_KIND)

    return docs.select(docs["doc_id"].cast("long").alias("doc_id"), text_of(docs).alias("text")).mapInArrow(cut, _PIECES)


def best_fit(counts: dict[int, int], size: int = SIZE) -> Counter:
    """Best fit by falling length over a histogram: {pattern of lengths: number of bins}."""
    room: list[Counter] = [Counter() for _ in range(size + 1)]
    for n in sorted(counts, reverse=True):
        left = counts[n]
        while left:
            r = next((r for r in range(n, size) if room[r]), None)
            if r is None:
                per = size // n
                if left >= per:
                    room[size - per * n][(n,) * per] += left // per
                if left % per:
                    room[size - left % per * n][(n,) * (left % per)] += 1
                left = 0
                continue
            pattern, have = next(iter(room[r].items()))
            take = min(have, left)
            room[r][pattern] -= take
            if not room[r][pattern]:
                del room[r][pattern]
            room[r - n][(*pattern, n)] += take
            left -= take
    out: Counter = Counter()
    for c in room:
        for p, k in c.items():
            out[tuple(sorted(p, reverse=True))] += k
    return out


def _exchanges(give: tuple, take: tuple, room: int):
    """(pieces that leave give, pieces that leave take, growth of take): moves, 1:1, 2:1 and 1:2."""
    singles, others = sorted(set(give), reverse=True), sorted(set(take), reverse=True)
    for a in singles:
        if a <= room:
            yield (a,), (), a
        for b in others:
            if 0 < a - b <= room:
                yield (a,), (b,), a - b
        for i, b in enumerate(take):
            for c in take[i + 1 :]:
                if 0 < a - b - c <= room:
                    yield (a,), (b, c), a - b - c
    for i, a in enumerate(give):
        for c in give[i + 1 :]:
            for b in others:
                if 0 < a + c - b <= room:
                    yield (a, c), (b,), a + c - b


def _without(p: tuple, gone: tuple, new: tuple) -> tuple:
    left = list(p)
    for g in gone:
        left.remove(g)
    return tuple(sorted((*left, *new), reverse=True))


def _best(give: tuple, takes: list[tuple[int, tuple]], size: int):
    """(gain, pieces that leave give, pattern that takes, pieces that leave it) of the best exchange, or None."""
    full, best = sum(give), None
    for fill, take in takes:
        for gone, back, grow in _exchanges(give, take, size - fill):
            gain = (fill + grow) ** 2 + (full - grow) ** 2 - fill**2 - full**2
            if gain > 0 and (best is None or gain > best[0]):
                best = (gain, gone, take, back)
        if best and best[0] >= 2 * (size - 1 - full):
            break
    return best


def improve(bins: Counter, size: int = SIZE) -> Counter:
    """Local search by exchanges that raise the sum of squared fills, until bins cannot be fewer or no exchange is left."""
    bins, fewest = Counter(bins), -(-sum(sum(p) * k for p, k in bins.items()) // size)
    under = sorted((sum(p), p) for p in bins if sum(p) < size)
    born, clock, done = {p: 0 for _, p in under}, 0, {}
    while bins.total() > fewest:
        for full, give in under:  # emptiest first; a donor looks only at patterns that came up since it last found nothing
            last = done.get(give, -1)
            alone = bins[give] < 2
            takes = [(f, p) for f, p in reversed(under[bisect_left(under, (full, ())) :]) if born[p] > last and not (alone and p == give)]
            if found := _best(give, takes, size):
                break
            done[give] = clock
        else:
            break
        _, gone, take, back = found
        k = bins[give] // 2 if give == take else min(bins[give], bins[take])
        clock += 1
        for old, new in ((give, _without(give, gone, back)), (take, _without(take, back, gone))):
            bins[old] -= k
            if not bins[old]:
                del bins[old]
                del under[bisect_left(under, (sum(old), old))]
                del born[old]
                done.pop(old, None)
            if new:
                if new not in bins and sum(new) < size:
                    insort(under, (sum(new), new))
                    born[new] = clock
                elif bins.get(new) == 1 and sum(new) < size:
                    born[new] = clock  # two of a kind may exchange with each other
                bins[new] += k
    return bins


def places(bins: Counter) -> dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """For each length: first ranks, first sequence ids and offsets of its runs of places."""
    used, runs, base = defaultdict(int), defaultdict(list), 0
    for pattern, k in sorted(bins.items(), reverse=True):
        at = 0
        for n in pattern:
            runs[n].append((used[n], base, at))
            used[n] += k
            at += n
        base += k
    return {n: tuple(np.array(c, np.int64) for c in zip(*r)) for n, r in runs.items()}


def pack(docs: DataFrame, size: int = SIZE, end: int = END, tokenizer: str | None = None) -> tuple[DataFrame, DataFrame]:
    """(placed, pieces): a row per piece with its sequence and offset; the written pieces with their ids."""
    cut = written(pieces(docs, size, end, tokenizer), "pieces")
    counts = cut.groupBy("part", "length").agg(F.count("*").alias("n"))
    before = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    counts = written(counts.withColumn("before", F.coalesce(F.sum("n").over(before), F.lit(0))), "lengths")
    total = {int(r[0]): int(r[1]) for r in counts.groupBy("length").agg(F.sum("n")).collect()}  # at most ``size`` rows
    at = places(improve(best_fit(total, size), size))

    def place(frames):
        for f in frames:
            rank, length = (f["before"] + f["nth"]).to_numpy(), f["length"].to_numpy()
            seq, off = np.zeros(len(f), np.int64), np.zeros(len(f), np.int64)
            for n in np.unique(length):
                first, base, offset = at[int(n)]
                mine = np.flatnonzero(length == n)
                run = np.searchsorted(first, rank[mine], side="right") - 1
                seq[mine], off[mine] = base[run] + rank[mine] - first[run], offset[run]
            yield pd.DataFrame({"part": f["part"], "length": f["length"], "nth": f["nth"], "doc_id": f["doc_id"].astype("Int64"),
                                "piece": f["piece"], "start": f["start"], "ids_crc32": f["ids_crc32"],
                                "sequence_id": seq, "offset": off})

    # parts x lengths rows grow with the input, so the two meet by a shuffle of the thin columns and never by broadcast
    small = cut.drop("ids").join(counts.drop("n").hint("merge"), ["part", "length"])
    out = small.mapInPandas(
        place, "part int, length long, nth long, doc_id long, piece int, start long, ids_crc32 long, sequence_id long, offset long"
    )
    return out.select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset", "part", "nth"), cut


def sequences(docs: DataFrame, size: int = SIZE, end: int = END, tokenizer: str | None = None) -> DataFrame:
    """The packed sequences themselves: sequence_id, n_tokens, ids (raw little-endian, in order of offset)."""
    placed, cut = pack(docs, size, end, tokenizer)
    body = cut.select("part", "length", "nth", "ids")
    rows = placed.join(body, ["part", "length", "nth"]).select("sequence_id", F.struct("offset", "ids").alias("p"), "length")
    joined = rows.groupBy("sequence_id").agg(F.sum("length").alias("n_tokens"), F.array_sort(F.collect_list("p")).alias("p"))
    return joined.select("sequence_id", "n_tokens", F.aggregate("p", F.lit(b""), lambda a, x: F.concat(a, x["ids"])).alias("ids"))
