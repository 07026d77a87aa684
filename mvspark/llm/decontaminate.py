"""Benchmark passages in documents by Wu-Manber multi-pattern search over words.

Patterns are the benchmark's windows of ``window`` words (an item of fewer words is one
window). Patterns of one length form a set. A table over blocks of two adjacent words says how
far the search may move on; a block in no pattern skips window-1 words. Where the shift is zero
the block is a suffix of some patterns: those in the bucket of that suffix are compared word by
word. Items are loaded in blocks of at most ``block_words`` words, so what a task holds does not
grow with the benchmark; every block searches every whole document.

Defined results: null or wordless text has no words and is clean; wordless items are ignored;
null item_ids are ignored; items with the same words are all reported; repeated document rows
are judged one by one; an empty benchmark leaves all clean; other columns are ignored.
"""

import hashlib
from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

WINDOW = 10
BLOCK_WORDS = 1_000_000

#: lower-cases A-Z and turns all bytes that end a word into spaces
_TABLE = bytes(
    c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256)
)


def words(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").translate(_TABLE).split()


class PatternSet:
    """Shift table and suffix buckets for patterns of one length."""

    def __init__(self, length: int, patterns: dict[tuple, list[int]]):
        self.length, self.patterns = length, patterns
        self.width = min(2, length)
        self.longest = length - self.width + 1
        self.shift: dict[tuple, int] = {}
        self.bucket: dict[tuple, list[tuple]] = {}
        for p in patterns:
            for end in range(self.width, length + 1):
                block = p[end - self.width : end]
                self.shift[block] = min(self.shift.get(block, self.longest), length - end)
            self.bucket.setdefault(p[-self.width :], []).append(p)

    def find(self, text: list[bytes]) -> Iterator[tuple[int, list[int]]]:
        """Starts of occurrences with the numbers of their items."""
        length, width, far, shift = self.length, self.width, self.longest, self.shift.get
        at, n = length, len(text)
        while at <= n:
            block = (text[at - 2], text[at - 1]) if width == 2 else (text[at - 1],)
            move = shift(block, far)
            if move:
                at += move
                continue
            start = at - length
            first = text[start]
            for p in self.bucket[block]:
                if p[0] == first and tuple(text[start:at]) == p:
                    yield start, self.patterns[p]
            at += 1


def pattern_sets(items: list[tuple[int, list[bytes]]], window: int) -> list[PatternSet]:
    by_length: dict[int, dict[tuple, list[int]]] = {}
    for item, w in items:
        size = min(window, len(w))
        for i in range(len(w) - size + 1 if w else 0):
            owners = by_length.setdefault(size, {}).setdefault(tuple(w[i : i + size]), [])
            if not owners or owners[-1] != item:
                owners.append(item)
    return [PatternSet(n, p) for n, p in sorted(by_length.items())]


def item_blocks(benchmark: DataFrame, block_words: int) -> Iterator[list[tuple[int, list[bytes]]]]:
    """The items, streamed to the driver a partition at a time, in blocks of bounded size."""
    block, size = [], 0
    for item, text in benchmark.select("item_id", "text").where("item_id is not null").toLocalIterator():
        w = words(text)
        if block and size + len(w) > block_words:
            yield block
            block, size = [], 0
        block.append((item, w))
        size += len(w)
    if block:
        yield block


def find_passages(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_words: int = BLOCK_WORDS) -> DataFrame:
    """(doc_id, n_words, spans, items): merged hit spans [from, to) in words, and item ids found."""
    schema = "doc_id long, text string, n_words long, spans array<struct<lo:long,hi:long>>, items array<long>"
    kind = pa.schema([
        ("doc_id", pa.int64()), ("text", pa.string()), ("n_words", pa.int64()),
        ("spans", pa.list_(pa.struct([("lo", pa.int64()), ("hi", pa.int64())]))), ("items", pa.list_(pa.int64())),
    ])
    out = docs.select(
        docs["doc_id"].cast("long").alias("doc_id"), docs["text"].alias("text"), F.lit(0).cast("long").alias("n_words"),
        F.expr("cast(array() as array<struct<lo:bigint,hi:bigint>>)").alias("spans"),
        F.expr("cast(array() as array<bigint>)").alias("items"),
    )
    blocks = item_blocks(benchmark, block_words)
    block = next(blocks, [])
    while block is not None:
        following = next(blocks, None)

        def search(batches, block=block, last=following is None):
            sets = pattern_sets(block, window)
            for batch in batches:
                n_words, all_spans, all_items = [], [], []
                texts, spans, items = (batch.column(i).to_pylist() for i in (1, 3, 4))
                for text, old, had in zip(texts, spans, items):
                    w, found, got = words(text), [(s["lo"], s["hi"]) for s in old], set(had)
                    for s in sets:
                        for start, owners in s.find(w):
                            found.append((start, start + s.length))
                            got.update(owners)
                    n_words.append(len(w))
                    all_spans.append(merged(found))
                    all_items.append(sorted(got))
                kept = pa.nulls(len(n_words), pa.string()) if last else batch.column(1).cast(pa.string())
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0), kept, pa.array(n_words, pa.int64()),
                     pa.array(all_spans, kind.field("spans").type), pa.array(all_items, kind.field("items").type)],
                    schema=kind,
                )

        out = out.mapInArrow(search, schema)
        block = following
    return out.drop("text")


def merged(spans: list[tuple[int, int]]) -> list[dict]:
    out: list[dict] = []
    for lo, hi in sorted(spans):
        if out and lo <= out[-1]["hi"]:
            out[-1]["hi"] = max(out[-1]["hi"], hi)
        else:
            out.append({"lo": lo, "hi": hi})
    return out


def contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_words: int = BLOCK_WORDS) -> DataFrame:
    """One row per document with counts, a digest of the items found and the verdict."""
    found = find_passages(docs, benchmark, window, block_words)
    hit = F.aggregate("spans", F.lit(0).cast("long"), lambda n, s: n + s["hi"] - s["lo"])
    names = F.array_sort(F.transform("items", lambda i: i.cast("string")))
    return found.select(
        "doc_id", "n_words", hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join(names, ","), 256).alias("items_sha256"), (hit > 0).alias("contaminated"), "spans", "items",
    )


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_words: int = BLOCK_WORDS) -> DataFrame:
    """The rows of ``docs`` that hold no window of the benchmark, with their columns.

    The verdict is a filter on each row as it passes, so that no text is shuffled.
    """
    clean = docs
    for block in item_blocks(benchmark, block_words):
        clean = clean.where(_free_of(block, window)(clean["text"]))
    return clean


def _free_of(block: list, window: int):
    def free(texts: pd.Series) -> pd.Series:
        sets = _sets_of(block, window)
        return pd.Series([not any(any(True for _ in s.find(w)) for s in sets) for w in map(words, texts)], dtype=bool)

    return F.pandas_udf(free, "boolean")


_last: list = []


def _sets_of(block: list, window: int) -> list[PatternSet]:
    """The tables of the block last used in this worker."""
    key = (window, hashlib.sha256(repr(block).encode()).hexdigest())
    if not _last or _last[0] != key:
        _last[:] = [key, pattern_sets(block, window)]
    return _last[1]


SQL = r"""
WITH dw AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
                                    '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
bw AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
                                     '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
pat AS (
  SELECT DISTINCT item_id, least(10, len(w)) AS m, array_to_string(list_slice(w, i, i + least(10, len(w)) - 1), ' ') AS p
  FROM (SELECT item_id, w, unnest(range(1, greatest(1, len(w) - 9) + 1)) AS i FROM bw WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT m FROM pat),
win AS (
  SELECT doc_id, m, i, array_to_string(list_slice(w, i, i + m - 1), ' ') AS p
  FROM (SELECT doc_id, w, m, unnest(range(1, len(w) - m + 2)) AS i FROM dw, sizes WHERE len(w) >= m)),
occ AS (SELECT win.doc_id, win.m, win.i, pat.item_id FROM win JOIN pat USING (m, p)),
hits AS (SELECT doc_id, count(DISTINCT k) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + m)) AS k FROM occ) GROUP BY doc_id),
its AS (SELECT doc_id, count(*) AS n_items, string_agg(s, ',' ORDER BY s) AS ids
        FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS s FROM occ) GROUP BY doc_id)
SELECT dw.doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
       sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM dw LEFT JOIN hits USING (doc_id) LEFT JOIN its USING (doc_id)
"""
