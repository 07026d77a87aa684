"""Resharding by minimum-cost flow: from old shard sizes to new capacities, moving the fewest bytes.

Rows of an old shard fall into hash blocks, whose sizes reach the driver (old shards x blocks
numbers, whatever the input). A flow network from old to new shards, where staying is free and
each byte moved costs one, gives the bytes to carry from each old to each new shard. Along an old
shard's blocks these amounts are ranges of its running size, so nearly every block goes whole and
the few that lie on a border are split between two rows. Then the files of every shard that a row leaves or
enters are written anew and read back; shards that none does keep their files.

Defined results: null text has no bytes (size 1, crc32 0); null source or id hashes like any
value; repeated rows are placed one by one; an empty table gives an empty result; other columns
are carried along, whatever their names.
"""

from __future__ import annotations

from collections import defaultdict

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import shared_path, text_of, written

SHARDS = 8
OLD = 6
BLOCKS = 2048


def min_cost_flow(supply: list[int], demand: list[int], cost) -> dict[tuple[int, int], int]:
    """Cheapest flows {(i, j): amount} by shortest augmenting paths; cost(i, j) >= 0."""
    n, m = len(supply), len(demand)
    assert sum(supply) == sum(demand)
    left, need, flow = list(supply), list(demand), defaultdict(int)
    while any(left):
        dist = [0 if left[i] else float("inf") for i in range(n)] + [float("inf")] * m
        prev: list = [None] * (n + m)
        changed = True
        while changed:
            changed = False
            for i in range(n):
                for j in range(m):
                    if dist[i] + cost(i, j) < dist[n + j]:
                        dist[n + j], prev[n + j], changed = dist[i] + cost(i, j), i, True
                    if flow[i, j] and dist[n + j] - cost(i, j) < dist[i]:
                        dist[i], prev[i], changed = dist[n + j] - cost(i, j), n + j, True
        end = min((j for j in range(m) if need[j]), key=lambda j: dist[n + j])
        path, v = [], n + end
        while prev[v] is not None:
            path.append((prev[v], v))
            v = prev[v]
        amount = min([left[v], need[end], *(flow[b, a - n] for a, b in path if a >= n)])
        for a, b in path:
            if a < n:
                flow[a, b - n] += amount
            else:
                flow[b, a - n] -= amount
        left[v] -= amount
        need[end] -= amount
    return {k: f for k, f in flow.items() if f}


def layout(docs: DataFrame, old: Column, blocks: int = BLOCKS) -> DataFrame:
    """Today's files: (row, own, size, crc, block, old_shard), partitioned by old shard, in the shared folder.

    ``row`` holds the columns of ``docs`` whatever their names; ``own`` tells repeated rows apart; ``old`` gives a row's shard.
    """
    text, key = text_of(docs), F.col("doc_id")
    rows = docs.select(
        F.struct(*(docs[c] for c in docs.columns)).alias("row"), docs["doc_id"].alias("doc_id"), F.monotonically_increasing_id().alias("own"),
        (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("crc"), old.cast("int").alias("old_shard"),
    )
    rows = rows.withColumn("block", F.pmod(F.xxhash64(key, "crc", "own"), F.lit(blocks)).cast("int"))
    return written(rows.drop("doc_id"), "layout", by="old_shard")


def plan(rows: DataFrame, n_old: int = OLD, n_new: int = SHARDS) -> tuple[Column, dict, dict, int]:
    """(shard of a row with column ``mid``, first byte of each block, flow, total) from a layout's block sizes."""
    sizes: dict[int, dict[int, int]] = defaultdict(dict)
    for o, b, s in rows.groupBy("old_shard", "block").agg(F.sum("size")).collect():  # n_old x blocks rows at most
        sizes[o][b] = s
    supply = [sum(sizes[i].values()) for i in range(n_old)]
    total = sum(supply)
    demand = [total * (j + 1) // n_new - total * j // n_new for j in range(n_new)]
    flow = min_cost_flow(supply, demand, lambda i, j: int(i != j))
    starts = {}
    for o, by in sizes.items():
        at = 0
        for b in sorted(by):
            starts[o, b] = (at, at + by[b])
            at += by[b]
    shard = F.lit(n_new - 1)
    for o in range(n_old):
        at, inner = 0, None
        for j in sorted((j for i, j in flow if i == o), key=lambda j: (j != o, j)):
            at += flow[o, j]
            inner = F.when(F.col("mid") < at, j) if inner is None else inner.when(F.col("mid") < at, j)
            last = j
        if inner is not None:
            shard = F.when(F.col("old_shard") == o, inner.otherwise(last)).otherwise(shard)
    return shard.cast("int"), starts, flow, total


def place(rows: DataFrame, n_old: int = OLD, n_new: int = SHARDS) -> DataFrame:
    """(own, size, old_shard, block, shard, slot) of every row of a layout; texts are not read."""
    thin = rows.select("own", "size", "old_shard", "block")
    spark = rows.sparkSession
    shard, starts, _, _ = plan(thin, n_old, n_new)
    begin = spark.createDataFrame([(o, b, lo) for (o, b), (lo, _) in starts.items()], "old_shard int, block int, begin long")
    run = F.sum("size").over(Window.partitionBy("old_shard", "block").orderBy("own").rowsBetween(Window.unboundedPreceding, 0))
    placed = thin.join(F.broadcast(begin), ["old_shard", "block"]).withColumn("mid", F.col("begin") + run - (F.col("size") / 2))
    placed = written(placed.withColumn("shard", shard).drop("mid", "begin"), "placed")
    counts = placed.groupBy("shard", "old_shard", "block").agg(F.count("*").alias("n")).collect()  # as bounded as the blocks
    first, offsets = defaultdict(int), []
    for s, o, b, n in sorted(tuple(r) for r in counts):
        offsets.append((s, o, b, first[s]))
        first[s] += n
    before = spark.createDataFrame(offsets, "shard int, old_shard int, block int, before long")
    nth = F.row_number().over(Window.partitionBy("shard", "old_shard", "block").orderBy("own"))
    out = placed.join(F.broadcast(before), ["shard", "old_shard", "block"])
    return out.select("own", "size", "old_shard", "block", "shard", (F.col("before") + nth - 1).cast("long").alias("slot"))


def rewrite(rows: DataFrame, placement: DataFrame, path: str) -> tuple[DataFrame, list[int]]:
    """(every row in its new shard, the shards written): affected shards are written to ``path``/shard=N, the rest keep their files.

    A shard is affected if a row leaves or enters it. The result is read back from the files: row, own, old_shard, shard, slot.
    """
    moves = placement.where("shard <> old_shard").groupBy("old_shard", "shard").count().collect()  # n_old x n_new rows at most
    touched = sorted({x for o, s, _ in moves for x in (o, s)})
    still = [r[0] for r in placement.select("old_shard").distinct().collect() if r[0] not in touched]
    go = placement.where(F.col("shard").isin(touched)).select("own", "shard", "slot")
    spark = rows.sparkSession
    body = rows.select("row", "own", "old_shard").where(F.col("old_shard").isin(touched))
    new = body.join(go, "own")
    new.write.partitionBy("shard").option("compression", "zstd").mode("overwrite").parquet(path)
    cols = ["row", "own", "old_shard", "shard", "slot"]
    back = spark.read.schema(new.schema).parquet(path).select(cols)
    if still:
        kept = rows.where(F.col("old_shard").isin(still)).join(placement.select("own", "shard", "slot"), "own")
        back = back.unionByName(kept.select(cols))
    return back, touched


def reshard(docs: DataFrame, old: Column, n_old: int = OLD, n_new: int = SHARDS, blocks: int = BLOCKS) -> DataFrame:
    """One row per document, read back from the rewritten shards: doc_id, size, text_crc32, old_shard, shard, slot, moved.

    ``old`` gives a row's shard today, 0 to n_old-1; shard i stays shard i where it can.
    """
    rows = layout(docs, old, blocks)
    out, _ = rewrite(rows, place(rows, n_old, n_new), shared_path(docs.sparkSession, "shards"))
    text = F.coalesce(F.col("row.text").cast("string"), F.lit(""))
    return out.select(
        F.col("row.doc_id").alias("doc_id"), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"),
        "old_shard", "shard", "slot", (F.col("shard") != F.col("old_shard")).alias("moved"),
    )
