"""Which worker holds which object: hashed shards, or shards of like objects; and how many there should be."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: bytes of token vectors that one shard may hold, so that it fits a worker beside its graph
SHARD_BYTES = 256 << 20
#: objects at most from which centres are fitted, the least by a hash of their ids
SAMPLE = 20_000


def rows_of(column) -> tuple[np.ndarray, np.ndarray]:
    """(tokens as rows, tokens of each object) of an Arrow column of arrays of arrays."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
        if isinstance(column, pa.ChunkedArray):
            column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], column.type)
    size = np.asarray(column.value_lengths().fill_null(0), np.int64)
    inner = column.flatten()
    flat = inner.flatten().to_numpy(zero_copy_only=False)
    n = int(size.sum())
    return flat.reshape(n, -1) if n else np.zeros((0, 1)), size


def n_shards(objs: DataFrame, limit: int = SHARD_BYTES) -> int:
    """As many shards as keep each below ``limit`` bytes of 4-byte coordinates."""
    n = objs.agg(F.sum(F.size("vecs") * F.size(F.col("vecs")[0]))).first()[0] or 0
    return max(1, math.ceil(4 * n / limit))


def pooled(x: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Unit mean vector of each object."""
    if not len(size):
        return np.zeros((0, 1))
    total = np.add.reduceat(x.astype(np.float64), np.cumsum(size) - size)
    return total / np.maximum(np.linalg.norm(total, axis=1, keepdims=True), 1e-300)


def fit_centres(objs: DataFrame, n: int, rounds: int = 10, sample: int = SAMPLE) -> np.ndarray:
    """n centres of mean token vectors, from a bounded sample; every object is routed by them later."""
    chosen = objs.select("mv_id").orderBy(F.xxhash64("mv_id"), "mv_id").limit(sample)

    def means(batches):
        for b in batches:
            x = pooled(*rows_of(b.column(2)))
            lists = pa.ListArray.from_arrays(pa.array(np.arange(b.num_rows + 1, dtype=np.int32) * x.shape[1]), pa.array(x.ravel()))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), lists], names=["h", "mv_id", "mean"])

    # objects become their means where they lie: the driver gets one vector of each
    some = objs.join(chosen, "mv_id", "left_semi").select(F.xxhash64("mv_id").alias("h"), "mv_id", "vecs").mapInArrow(means, "h long, mv_id long, mean array<double>").toArrow()
    if not len(some):
        return np.zeros((0, 0))
    order = np.lexsort((some.column("mv_id").to_numpy(), some.column("h").to_numpy()))
    x = some.column("mean").combine_chunks().flatten().to_numpy().reshape(len(order), -1)[order]
    c = x[np.linspace(0, len(x) - 1, min(n, len(x))).astype(int)]
    for _ in range(rounds):
        own = (x @ c.T).argmax(1)
        c = np.stack([x[own == i].mean(0) if (own == i).any() else c[i] for i in range(len(c))])
        c /= np.maximum(np.linalg.norm(c, axis=1, keepdims=True), 1e-300)
    return c


def route_objects(objs: DataFrame, centres: np.ndarray) -> DataFrame:
    """``objs`` with the shard of its nearest centre; graphs built from it keep that shard."""

    def run(batches):
        for b in batches:
            x, size = rows_of(b.column(2))
            own = (pooled(x, size) @ centres.T).argmax(1).astype(np.int32) if len(size) else np.zeros(0, np.int32)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(own)], names=["mv_id", "n_tok", "vecs", "shard"])

    return objs.select("mv_id", "n_tok", "vecs").mapInArrow(run, "mv_id long, n_tok int, vecs array<array<double>>, shard int")


def single(column: str = "vecs") -> Column:
    """Token vectors in single precision, as graphs and links hold them: half the bytes on the way to a worker."""
    return F.col(column).cast("array<array<float>>").alias(column)


def with_shards(objs: DataFrame, n: int) -> DataFrame:
    """Hashed shards, unless the objects come with theirs."""
    if "shard" in objs.columns:
        return objs
    return objs.withColumn("shard", F.pmod(F.xxhash64("mv_id"), F.lit(n)).cast("int"))
