"""Near-duplicates by SimHash and a generalised pigeonhole search in Hamming space.

The 64 bits are grouped into ``PARTS`` partitions that hold correlated bits together. If two
fingerprints differ in at most r bits and the partitions' thresholds sum to r - PARTS + 1
(-1 skips a partition), some partition differs by at most its threshold. For every fingerprint a
dynamic programme picks the thresholds with the fewest expected candidates, from counts of all
fingerprints' partition values in a sketch of fixed size; its probes are joined with the values of
all fingerprints and verified. A fingerprint whose cheapest probes would still meet more than
``DENSE`` others sits in a dense ball; such fingerprints meet each other exactly on the
words within one bit of both (radius 2 is one step from each end), at most 65 rows each and 65 a key,
never on pairs. Equal fingerprints are one vertex; links are contracted to components.

Defined results: null text and text without words have fingerprint 0 and link like any other; texts
of fewer words than a shingle are one shingle; rows with one doc_id are one document; null ids
are last and, alone in a group, give a null component; an empty table gives an empty result; other
columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import components, text_of, without, written

SHINGLE = 3
RADIUS = 2
SEED = 42
PARTS = 3
#: bits of a sketch index (so 2^16 counters a partition reach the driver), and the most candidates a fingerprint may probe for
SKETCH, DENSE = 16, 64

_CHUNK = 100_000


def fingerprint(text: str | None, shingle: int = SHINGLE) -> int:
    """Unsigned 64-bit SimHash over word shingles; a bit is set if set in over half the shingles' XXH64."""
    from xxhash import xxh64_intdigest

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    line = b" ".join(words)
    if len(words) < shingle:
        return xxh64_intdigest(line, SEED)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])[: len(words) - shingle + 1]
    ends = ends[shingle - 1 :]
    n, ones = len(starts), np.zeros(64, np.int64)
    for i in range(0, n, _CHUNK):
        h = [xxh64_intdigest(line[a:b], SEED) for a, b in zip(starts[i : i + _CHUNK].tolist(), ends[i : i + _CHUNK].tolist())]
        raw = np.array(h, ">u8").view(np.uint8).reshape(-1, 8)
        ones += np.unpackbits(raw, axis=1).sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > n).view(">u8")[0])


def fingerprints(docs: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """(doc_id, fp, check): signed fingerprints of whole texts, and a hash that tells texts of one doc_id apart."""

    def run(batches):
        for b in batches:
            fp = np.array([fingerprint(t, shingle) for t in b.column(1).to_pylist()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fp), b.column(2)], names=["doc_id", "fp", "check"])

    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), text_of(docs).alias("text"), F.xxhash64(text_of(docs)).alias("check"))
    return rows.mapInArrow(run, "doc_id long, fp long, check long")


def _bits(fp: np.ndarray) -> np.ndarray:
    return ((fp[:, None].astype(np.uint64) >> np.arange(64, dtype=np.uint64)) & np.uint64(1)).astype(np.float64)


def correlated_parts(fps: DataFrame, parts: int = PARTS) -> list[list[int]]:
    """Bits grouped so that each partition holds correlated ones, from pair counts over all fingerprints."""

    def count(frames):
        total, n = np.zeros((64, 64)), 0
        for f in frames:
            for at in range(0, len(f), 50_000):
                b = _bits(f["fp"].to_numpy()[at : at + 50_000].view(np.uint64))
                total, n = total + b.T @ b, n + len(b)
        if n:
            i, j = np.triu_indices(64)
            yield pd.DataFrame({"i": np.append(i, -1), "j": np.append(j, -1), "n": np.append(total[i, j], n).astype(np.int64)})

    rows = fps.select("fp").mapInPandas(count, "i int, j int, n long").groupBy("i", "j").agg(F.sum("n").alias("n")).collect()
    both, n = np.zeros((64, 64)), 1
    for i, j, c in rows:  # 2081 at most
        if i < 0:
            n = c
        else:
            both[i, j] = both[j, i] = c
    p = both.diagonal() / n
    cov = both / n - np.outer(p, p)
    sd = np.sqrt(np.maximum(cov.diagonal(), 1e-12))
    corr = np.abs(cov / np.outer(sd, sd))
    np.fill_diagonal(corr, 0)
    free, out = list(range(64)), []
    for k in range(parts):
        size = len(free) // (parts - k)
        group = [max(free, key=lambda b: (corr[b, free].sum(), -b))]
        while len(group) < size:
            group.append(max((b for b in free if b not in group), key=lambda b: (corr[b, group].sum(), -b)))
        free = [b for b in free if b not in group]
        out.append(sorted(group))
    return out


def _mask(bits: list[int]) -> int:
    return int(np.array([sum(1 << b for b in bits)], np.uint64).view(np.int64)[0])


def allocate(costs: np.ndarray, budget: int) -> tuple[np.ndarray, np.ndarray]:
    """Thresholds summing to ``budget`` with the least total cost: costs[n, part, t + 1] for t = -1, 0, 1, ..."""
    n, parts, choices = costs.shape
    low = -parts
    span = budget - low + parts + 1
    best = np.full((n, span), np.inf)
    best[:, -low] = 0
    picks = []
    for k in range(parts):
        new, pick = np.full((n, span), np.inf), np.zeros((n, span), np.int8)
        for c in range(choices):
            shifted = np.full((n, span), np.inf)
            t = c - 1
            if t < 0:
                shifted[:, :t] = best[:, -t:]
            else:
                shifted[:, t:] = best[:, : span - t]
            shifted += costs[:, k, c][:, None]
            better = shifted < new
            new, pick = np.where(better, shifted, new), np.where(better, t, pick)
        best = new
        picks.append(pick)
    at = np.full(n, budget - low)
    cost, out = best[np.arange(n), at], np.zeros((n, parts), np.int8)
    for k in reversed(range(parts)):
        out[:, k] = picks[k][np.arange(n), at]
        at = at - out[:, k]
    return out, cost


def links(groups: DataFrame, radius: int = RADIUS, parts: int = PARTS, sketch: int = SKETCH, dense: int = DENSE) -> DataFrame:
    """Edges (a, b) between distinct fingerprints that connect all pairs within ``radius`` = 2 bits."""
    if radius != 2:
        raise ValueError("dense fingerprints meet on words one bit from each end: radius 2")
    fps = groups.select("fp")
    bits = correlated_parts(fps, parts)
    masks = [_mask(b) for b in bits]
    values = [F.struct(F.lit(k).alias("part"), F.col("fp").bitwiseAND(F.lit(m)).alias("val")) for k, m in enumerate(masks)]
    index = fps.select("fp", F.explode(F.array(*values)).alias("x")).select("x.part", "x.val", F.col("fp").alias("other"))
    fold = F.col("val")
    for s in range(sketch, 64, sketch):
        fold = fold.bitwiseXOR(F.shiftrightunsigned("val", s))
    cells = index.select("part", fold.bitwiseAND(F.lit((1 << sketch) - 1)).alias("cell")).groupBy("part", "cell").agg(F.count("*").alias("n"))
    table = np.zeros((parts, 1 << sketch), np.int64)
    got = cells.toPandas()  # parts x 2^sketch rows at most
    table[got["part"].to_numpy(), got["cell"].to_numpy()] = got["n"].to_numpy()

    def probe(frames):
        one = np.uint64(1)
        flips = [[(one << np.uint64(b), 1 << (b % sketch)) for b in group] for group in bits]
        for f in frames:
            for lo in range(0, len(f), 20_000):
                fp = f["fp"].to_numpy()[lo : lo + 20_000].view(np.uint64)
                costs = np.zeros((len(fp), parts, radius + 2))
                vals = []
                for k in range(parts):
                    v = fp & np.array([masks[k]], np.int64).view(np.uint64)[0]
                    vals.append(v)
                    cell = v.copy()
                    for s in range(sketch, 64, sketch):
                        cell ^= v >> np.uint64(s)
                    cell = (cell & np.uint64((1 << sketch) - 1)).astype(np.int64)
                    costs[:, k, 1] = 1 + table[k, cell]
                    near = sum(table[k, cell ^ c] + 1 for _, c in flips[k])
                    costs[:, k, 2] = costs[:, k, 1] + near
                    far = sum(table[k, cell ^ a ^ b] + 1 for i, (_, a) in enumerate(flips[k]) for _, b in flips[k][i + 1 :])
                    costs[:, k, 3] = costs[:, k, 2] + far
                chosen, cost = allocate(costs, radius - parts + 1)
                crowded = cost > dense + 64 * parts  # probes count as well as candidates
                out = []

                def emit(part, val, who):
                    out.append(pd.DataFrame({"part": np.full(len(val), part, np.int32), "val": val.view(np.int64), "fp": who.view(np.int64)}))

                for k in range(parts):
                    t = np.where(crowded, -1, chosen[:, k])
                    emit(k, vals[k][t >= 0], fp[t >= 0])
                    for i, (a, _) in enumerate(flips[k]):
                        if (t >= 1).any():
                            emit(k, vals[k][t >= 1] ^ a, fp[t >= 1])
                        if (t >= 2).any():
                            for b, _ in flips[k][i + 1 :]:
                                emit(k, vals[k][t >= 2] ^ a ^ b, fp[t >= 2])
                own = fp[crowded]
                if len(own):
                    emit(parts, own, own)
                    for b in range(64):
                        emit(parts, own ^ (one << np.uint64(b)), own)
                yield pd.concat(out)

    rows = written(fps.mapInPandas(probe, "part int, val long, fp long"), "probes")
    found = rows.where(F.col("part") < parts).join(index, ["part", "val"])
    found = found.where("fp <> other and bit_count(fp ^ other) <= 2").select(F.col("fp").alias("a"), F.col("other").alias("b"))
    hubs = rows.where(F.col("part") == parts).groupBy("val").agg(F.collect_set("fp").alias("m")).where("size(m) > 1")
    hubs = hubs.select(F.array_min("m").alias("a"), F.explode("m").alias("b")).where("a <> b")
    return found.unionByName(hubs)


def near_duplicates(docs: DataFrame, shingle: int = SHINGLE, radius: int = RADIUS, **search) -> DataFrame:
    """One row per row of ``docs``: doc_id, fingerprint (hex), component_id, and check."""
    fps = written(fingerprints(docs, shingle), "fingerprints")
    groups = written(fps.groupBy("fp").agg(F.min("doc_id").alias("low")), "groups")
    roots = components(links(groups, radius, **search), "near")
    joined = written(groups.join(roots, F.col("fp") == F.col("v"), "left").select("fp", "low", F.coalesce("root", "fp").alias("root")), "roots")
    lowest = joined.groupBy("root").agg(F.min("low").alias("component_id"))
    label = joined.join(lowest, "root").select("fp", "component_id")
    return fps.join(label, "fp").select(
        "doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id", "check"
    )


def drop_near_duplicates(docs: DataFrame, shingle: int = SHINGLE, radius: int = RADIUS, similar: float | None = None) -> DataFrame:
    """One document of each component, that of the smallest doc_id, with its columns.

    With ``similar`` (0.8, over shingles of five words) links between fingerprints are verified by Jaccard similarity of
    the shingle sets and completed by an exact join, so that every pair that similar is linked and no other.
    """
    if similar is not None:
        from . import near_copies

        if (shingle, similar) != (near_copies.SHINGLE, near_copies.SIMILAR):
            raise ValueError("verified links are made for five words and a similarity of 0.8")
        return near_copies.drop_near_copies(docs)
    return without(docs, near_duplicates(docs, shingle, radius).where("not (doc_id <=> component_id)"))
