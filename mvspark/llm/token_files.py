"""Token files: raw id payloads in key order with a minimal perfect hash index.

A shard file is: magic, version and sizes; the keys and first ids of its records; a minimal
perfect hash of its distinct keys (a displacement per bucket, then per slot a 32-bit fingerprint
and the record it names); the raw ids, 2 or 4 bytes each. A key costs one hash, one displacement, one
slot and one range of the payload, however large the shard, read by position. Fingerprints turn away keys that
are not there; the stored key settles the rest. A manifest table names the files in key order.

Defined results: null or empty text is its end id alone; a null doc_id sorts last and is read in
order but not by key; rows with one doc_id lie side by side, ordered by a hash of their text, and
the key names the first; an empty table makes no file; other columns are ignored.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import shared_path, text_of, written
from .tokenise import default_path, encoder

END = 0
#: ids in a shard file at most, but for a single longer document
SHARD_IDS = 8_000_000
#: words whose ids a worker keeps, about 200 bytes each
CACHE = 1_200_000
#: fixed values of the format: magic, keys per bucket of the hash, first mixing constants
MAGIC = b"MVTOKENS"
HEAD = struct.Struct("<8sIIQQQQ")
BUCKET = 4
#: displacements tried together
TRIES = 128

_MANIFEST = "part int, seq int, path string, n_docs long, n_tokens long, low long, high long"


def mix(x: np.ndarray, seed: int | np.ndarray) -> np.ndarray:
    """64-bit finaliser over keys and seeds."""
    with np.errstate(over="ignore"):
        z = x.astype(np.uint64) + (np.asarray(seed).astype(np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
        z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return z ^ (z >> np.uint64(31))


class PerfectHash:
    """Minimal perfect hash by displacements: buckets, largest first, each get one that fits."""

    def __init__(self, shift: np.ndarray, n: int):
        self.shift, self.n = shift, n

    @classmethod
    def build(cls, keys: np.ndarray) -> PerfectHash:
        n = len(keys)
        buckets = max(1, -(-n // BUCKET))
        shift = np.zeros(buckets, np.int64)
        if not n:
            return cls(shift, 0)
        home = (mix(keys, 0) % np.uint64(buckets)).astype(np.int64)
        order = np.argsort(home, kind="stable")
        edges = np.searchsorted(home[order], np.arange(buckets + 1))
        sizes = np.diff(edges)
        taken = np.zeros(n, bool)
        for b in np.argsort(-sizes, kind="stable"):
            if sizes[b] < 2:
                break
            own, d = keys[order[edges[b] : edges[b + 1]]], 1
            while True:  # many displacements at a time
                tries = np.arange(d, d + TRIES)
                slots = (mix(own[None, :], tries[:, None]) % np.uint64(n)).astype(np.int64)
                fits = np.flatnonzero(~taken[slots].any(axis=1))
                for k in fits.tolist():
                    if len(set(slots[k].tolist())) == len(own):
                        taken[slots[k]] = True
                        shift[b] = tries[k]
                        break
                else:
                    d += TRIES
                    continue
                break
        free = np.flatnonzero(~taken)
        single = np.flatnonzero(sizes == 1)
        shift[single] = -free[: len(single)] - 1  # buckets of one key name their slot
        return cls(shift, n)

    def slots(self, keys: np.ndarray) -> np.ndarray:
        if not self.n:
            return np.zeros(len(keys), np.int64)
        d = self.shift[(mix(keys, 0) % np.uint64(len(self.shift))).astype(np.int64)]
        return np.where(d < 0, -d - 1, (mix(keys, np.maximum(d, 0)) % np.uint64(self.n)).astype(np.int64))


def fingerprints(keys: np.ndarray) -> np.ndarray:
    return (mix(keys, 0x5BD1E995) >> np.uint64(32)).astype("<u4")


def pack_shard(keys: list, payloads: list[bytes], width: int) -> bytes:
    """The bytes of a shard file."""
    null = np.array([k is None for k in keys], np.uint8)
    ids = np.array([k or 0 for k in keys], "<i8")
    offsets = np.concatenate([[0], np.cumsum([len(p) // width for p in payloads])]).astype("<u8")
    live = np.flatnonzero(null == 0)
    known, first = np.unique(ids[live], return_index=True)
    known, first = known.view(np.uint64) if len(known) else known.astype(np.uint64), live[first]
    index = PerfectHash.build(known)
    at = index.slots(known)
    prints, record = np.zeros(len(known), "<u4"), np.zeros(len(known), "<u4")
    prints[at], record[at] = fingerprints(known), first
    head = HEAD.pack(MAGIC, 1, width, len(keys), len(known), len(index.shift), int(offsets[-1]))
    return b"".join([head, null.tobytes(), ids.tobytes(), offsets.tobytes(), index.shift.astype("<i8").tobytes(),
                     prints.tobytes(), record.tobytes(), *payloads])


def _store(path: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(path)


class Shard:
    """A shard file opened for keyed or sequential reading.

    Opening reads the head alone. ``get`` then reads one displacement, one slot, one key, two offsets and one range
    of the payload, whatever the shard holds; ``find`` on many keys and ``records`` read whole columns once.
    """

    def __init__(self, path: str):
        store, at = _store(path)
        self.file, self.reads = store.open_input_file(at), 0
        magic, version, self.width, self.n, self.known, self.buckets, self.n_tokens = HEAD.unpack(self._read(HEAD.size, 0))
        if magic != MAGIC or version != 1:
            raise ValueError(f"{path} is no token file")
        sizes = {"null": ("u1", self.n), "keys": ("<i8", self.n), "offsets": ("<u8", self.n + 1), "shift": ("<i8", self.buckets),
                 "prints": ("<u4", self.known), "record": ("<u4", self.known)}
        self.place, at = {}, HEAD.size
        for name, (kind, count) in sizes.items():
            self.place[name] = (np.dtype(kind), at, count)
            at += np.dtype(kind).itemsize * count
        self.body = at
        self.whole: dict[str, np.ndarray] = {}

    def _read(self, n: int, at: int) -> bytes:
        self.reads += n
        return self.file.read_at(n, at)

    def some(self, name: str, at: int, n: int = 1) -> np.ndarray:
        """``n`` values of a column from place ``at``."""
        if name in self.whole:
            return self.whole[name][at : at + n]
        kind, base, _ = self.place[name]
        return np.frombuffer(self._read(kind.itemsize * n, base + kind.itemsize * at), kind)

    def column(self, name: str) -> np.ndarray:
        if name not in self.whole:
            self.whole[name] = self.some(name, 0, self.place[name][2])
        return self.whole[name]

    def find(self, keys) -> np.ndarray:
        """Record numbers of many keys, -1 where absent."""
        keys = np.asarray(keys, "<i8").view(np.uint64)
        if not self.known:
            return np.full(len(keys), -1, np.int64)
        at = PerfectHash(self.column("shift").astype(np.int64), self.known).slots(keys)
        r = self.column("record")[at].astype(np.int64)
        return np.where((self.column("prints")[at] == fingerprints(keys)) & (self.column("keys")[r].view(np.uint64) == keys), r, -1)

    def locate(self, key: int) -> int:
        """Record number of one key, -1 where absent, by a fixed number of small reads."""
        if not self.known:
            return -1
        one = np.array([key], "<i8").view(np.uint64)
        d = int(self.some("shift", int(mix(one, 0)[0] % np.uint64(self.buckets)))[0])
        slot = -d - 1 if d < 0 else int(mix(one, d)[0] % np.uint64(self.known))
        if self.some("prints", slot)[0] != fingerprints(one)[0]:
            return -1
        r = int(self.some("record", slot)[0])
        return r if int(self.some("keys", r)[0]) == key else -1

    def ids(self, record: int) -> np.ndarray:
        lo, hi = (int(x) for x in self.some("offsets", record, 2))
        return np.frombuffer(self._read((hi - lo) * self.width, self.body + lo * self.width), f"<u{self.width}")

    def get(self, key: int) -> np.ndarray | None:
        r = self.locate(key)
        return None if r < 0 else self.ids(r)


def write_token_files(docs: DataFrame, path: str, end: int = END, tokenizer: str | None = None, shard_ids: int = SHARD_IDS) -> DataFrame:
    """Encode whole texts, write shard files in ascending doc_id under ``path`` and return their manifest."""
    vocab = tokenizer or default_path()

    def write(batches):
        enc, part, seq = encoder(vocab, CACHE), TaskContext.get().partitionId(), 0
        attempt = TaskContext.get().taskAttemptId()
        tail = np.array([end], enc.kind).tobytes()
        store, base = _store(path)
        store.create_dir(base, recursive=True)
        keys, payloads, held = [], [], 0

        def flush():
            nonlocal keys, payloads, held, seq
            name = f"tokens-{part:06d}-{seq:05d}.mvt"
            with store.open_output_stream(f"{base}/.{name}.{attempt}") as f:
                f.write(pack_shard(keys, payloads, enc.width))
            store.move(f"{base}/.{name}.{attempt}", f"{base}/{name}")  # whole files only, whichever attempt ends first
            live = [k for k in keys if k is not None]
            row = (part, seq, f"{path}/{name}", len(keys), held, min(live, default=None), max(live, default=None))
            keys, payloads, held, seq = [], [], 0, seq + 1
            return pa.RecordBatch.from_arrays(
                [pa.array([v], t) for v, t in zip(row, (pa.int32(), pa.int32(), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.int64()))],
                names=["part", "seq", "path", "n_docs", "n_tokens", "low", "high"],
            )

        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                some = batch.slice(at, 1000)
                for doc, raw in zip(some.column(0).to_pylist(), enc.ids(some.column(1).to_pylist())):
                    if payloads and held + len(raw) // enc.width + 1 > shard_ids:
                        yield flush()
                    keys.append(doc)
                    payloads.append(raw + tail)
                    held += len(payloads[-1]) // enc.width
        if keys:
            yield flush()

    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), text_of(docs).alias("text"))
    order = [F.col("doc_id").asc_nulls_last(), F.xxhash64("text")]
    parts = max(1, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    dealt = rows.repartitionByRange(parts, *order).sortWithinPartitions(*order)
    return written(dealt.mapInArrow(write, _MANIFEST), "manifest")


def with_starts(manifest: DataFrame) -> DataFrame:
    """The manifest with ``before``: ids of all files before each. Partitions are as few as the shuffle's."""
    parts = manifest.groupBy("part").agg(F.sum("n_tokens").alias("n"))
    earlier = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    parts = parts.select("part", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("base"))
    inside = Window.partitionBy("part").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)
    out = manifest.join(parts, "part")
    return out.withColumn("before", F.col("base") + F.coalesce(F.sum("n_tokens").over(inside), F.lit(0))).drop("base")


def read_token_files(manifest: DataFrame) -> DataFrame:
    """Every record of the files: doc_id, start, n_tokens, ids_crc32, ids; each key is also found through the index."""
    files = max(1, manifest.count())
    kind = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())])

    def read(batches):
        for batch in batches:
            for path, before in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                shard = Shard(path)
                null, keys = shard.column("null"), shard.column("keys")
                live = np.flatnonzero(null == 0)
                found = shard.find(keys[live])
                if (found < 0).any() or (keys[found] != keys[live]).any():
                    raise ValueError(f"the index of {path} misses keys")
                a = shard.column("offsets").astype(np.int64)
                for lo in range(0, shard.n, 2000):
                    hi = min(shard.n, lo + 2000)
                    raw = shard.file.read_at(int(a[hi] - a[lo]) * shard.width, shard.body + int(a[lo]) * shard.width)
                    wide = np.frombuffer(raw, f"<u{shard.width}").astype("<u4")
                    crc = [zlib.crc32(wide[x:y]) for x, y in zip((a[lo:hi] - a[lo]).tolist(), (a[lo + 1 : hi + 1] - a[lo]).tolist())]
                    yield pa.RecordBatch.from_arrays([
                        pa.array(keys[lo:hi], pa.int64(), mask=null[lo:hi] != 0), pa.array(before + a[lo:hi]),
                        pa.array(np.diff(a[lo : hi + 1])), pa.array(crc, pa.int64())], schema=kind)

    dealt = with_starts(manifest).select("path", "before").repartition(min(files, 20_000), "path")
    return dealt.mapInArrow(read, "doc_id long, start long, n_tokens long, ids_crc32 long")


def fetch(manifest: DataFrame, keys: DataFrame) -> DataFrame:
    """Ids by key: (doc_id, ids array) for the doc_ids of ``keys`` that are in the files, through the index.

    A key finds its partitions in the list of their spans (as many as the writing shuffle had, whatever the
    input), meets their files by an equi-join and is then looked up in one file. A lookup reads a few small
    ranges; only where a task has many keys of one file does it read the index columns once.
    """
    spans = manifest.where("low is not null").select("path", "part", "low", "high")
    parts = spans.groupBy("part").agg(F.min("low").alias("low"), F.max("high").alias("high")).orderBy("low").collect()
    lows, highs = (np.array([r[c] for r in parts], np.int64) for c in ("low", "high"))
    names = np.array([r.part for r in parts], np.int64)
    reach = np.maximum.accumulate(highs) if len(highs) else highs  # spans touch where one doc_id is in two partitions

    def route(batches):
        for b in batches:
            k = b.column(0).to_numpy()
            first, end = np.searchsorted(reach, k, side="left"), np.searchsorted(lows, k, side="right")
            n = np.maximum(end - first, 0)
            at = np.repeat(first, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(k, n)), pa.array(names[at].astype(np.int32))], names=["doc_id", "part"])

    asked = keys.select(F.col("doc_id").cast("long").alias("doc_id")).where("doc_id is not null").distinct()
    hit = asked.mapInArrow(route, "doc_id long, part int").join(spans, "part").where(F.col("doc_id").between(F.col("low"), F.col("high")))

    def get(batches):
        shard, path = None, None
        for b in batches:
            docs, found = [], []
            column = b.column(0).to_pylist()
            for i, k in enumerate(b.column(1).to_pylist()):
                if column[i] != path:
                    path = column[i]
                    shard = Shard(path)
                    many = column[i:].count(path)
                    if many * 64 > shard.known:  # cheaper to read the columns once
                        for name in ("shift", "prints", "record", "keys", "offsets"):
                            shard.column(name)
                ids = shard.get(k)
                if ids is not None:
                    docs.append(k)
                    found.append(ids.astype(np.int64))
            yield pa.RecordBatch.from_arrays([pa.array(docs, pa.int64()), pa.array(found, pa.list_(pa.int64()))], names=["doc_id", "ids"])

    dealt = hit.select("path", "doc_id").repartition("path").sortWithinPartitions("path", "doc_id")
    out = dealt.mapInArrow(get, "doc_id long, ids array<long>")
    return out.dropDuplicates(["doc_id"])  # rows with one doc_id may lie in two files


def encode_to_files(docs: DataFrame, end: int = END, tokenizer: str | None = None, path: str | None = None) -> DataFrame:
    """Write token files (in the shared folder unless a path is given) and read them back."""
    at = path or shared_path(docs.sparkSession, "tokens")
    return read_token_files(write_token_files(docs, at, end, tokenizer))
