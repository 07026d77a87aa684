import zlib
from collections import Counter, defaultdict
from itertools import combinations

import numpy as np
import pytest

from mvspark.llm import packing, token_files
from mvspark.llm.tokenise import default_path, encoder


@pytest.fixture(scope="module")
def plain():
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(default_path())
    return lambda s: t.encode(s or "", add_special_tokens=False).ids


def crc(ids):
    return zlib.crc32(np.array(ids, "<u4").tobytes())


def test_cached_encoder_equals_whole_texts(edge_rows, plain, spark, sf):
    texts = [t or "" for _, t in edge_rows] + [r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    enc = encoder(default_path())
    for t, raw in zip(texts, enc.ids(texts)):
        assert np.frombuffer(raw, enc.kind).tolist() == plain(t)


def test_added_tokens_are_the_librarys(plain):
    texts = ["end <|endoftext|> here", "<|endoftext|>", "a<|endoftext|><|endoftext|>b", "<|endof text|>", "plain text", "<|endoftext|", ""]
    enc = encoder(default_path())
    assert [np.frombuffer(raw, enc.kind).tolist() for raw in enc.ids(texts)] == [plain(t) for t in texts]
    assert len(plain(texts[0])) == 4


def test_packing(edge, edge_rows, plain, empty):
    placed, cut = packing.pack(edge, size=64)
    got = placed.collect()
    want, total = Counter(), 0
    for i, t in edge_rows:
        ids = [*plain(t), 2]
        total += len(ids)
        edges = [0, *range((len(ids) - 1) % 64 + 1, len(ids) + 1, 64)]
        for k, (lo, hi) in enumerate(zip(edges, edges[1:])):
            want[i, k, lo, hi - lo, crc(ids[lo:hi])] += 1
    assert Counter((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in got) == want
    bins = defaultdict(list)
    for r in got:
        bins[r.sequence_id].append((r.offset, r.length))
    for b in bins.values():
        at = 0
        for off, n in sorted(b):
            assert off == at
            at += n
        assert at <= 64
    assert len(bins) <= -(-total // 64) + 1
    assert packing.pack(empty)[0].count() == 0


def test_local_search_improves():
    rng = np.random.default_rng(3)
    for seed in range(6):
        counts = Counter(rng.integers(20, 60, 120).tolist())
        first = Counter({(n,): c for n, c in counts.items()})
        better = packing.improve(first, 100)
        assert Counter(x for p, k in better.items() for x in p * k) == counts
        assert all(sum(p) <= 100 for p in better)
        assert better.total() < first.total()
        fit = packing.best_fit(dict(counts), 100)
        assert Counter(x for p, k in fit.items() for x in p * k) == counts
        assert packing.improve(fit, 100).total() <= fit.total()
        assert better.total() == -(-sum(n * c for n, c in counts.items()) // 100) or no_exchange(better, 100)


def no_exchange(bins, size):
    """By trying every move, 1:1, 2:1 and 1:2 exchange of every two bins."""
    def sides(p):
        return [()] + [(x,) for x in p] + list(combinations(p, 2))

    under = [p for p in bins if sum(p) < size]
    for p in under:
        for q in under:
            if sum(p) > sum(q) or (p == q and bins[p] < 2):
                continue
            for a in sides(p):
                for b in sides(q):
                    grow = sum(a) - sum(b)
                    if a and (len(a), len(b)) in ((1, 0), (1, 1), (1, 2), (2, 1)) and 0 < grow <= size - sum(q):
                        return False
    return True


def test_sequences(edge, plain, edge_rows):
    rows = packing.sequences(edge, size=64).collect()
    assert sum(r.n_tokens for r in rows) == sum(len(plain(t)) + 1 for _, t in edge_rows)
    assert all(len(r.ids) == 2 * r.n_tokens <= 128 for r in rows)


def test_token_files(edge, edge_rows, plain, empty, spark, tmp_path):
    manifest = token_files.write_token_files(edge, f"file://{tmp_path}/t", shard_ids=500)
    assert manifest.count() > 4
    got = sorted(token_files.read_token_files(manifest).collect(), key=lambda r: r.start)
    at, ids = 0, [r.doc_id for r in got]
    assert ids == sorted((i for i in ids if i is not None)) + [None] * 2
    for r in got:
        assert r.start == at
        at += r.n_tokens
    assert Counter((r.doc_id, r.n_tokens, r.ids_crc32) for r in got) == Counter(
        (i, len(plain(t)) + 1, crc([*plain(t), 0])) for i, t in edge_rows
    )
    asked = spark.createDataFrame([(7,), (999,), (-7,), (None,), (34,)], "doc_id long")
    found = {r.doc_id: r.ids for r in token_files.fetch(manifest, asked).collect()}
    text = dict(edge_rows)
    assert found == {i: [*plain(text[i]), 0] for i in (7, -7, 34)}
    assert token_files.encode_to_files(empty).count() == 0
    assert token_files.fetch(manifest.limit(0), asked).count() == 0


def test_keyed_read_is_constant(tmp_path):
    payload = [np.arange(20, dtype="<u2").tobytes()] * 50_000
    read = {}
    for n in (100, 50_000):
        path = tmp_path / f"{n}.mvt"
        path.write_bytes(token_files.pack_shard([3 * i for i in range(n)], payload[:n], 2))
        shard = token_files.Shard(str(path.as_uri()))
        assert shard.get(3 * (n - 1)).tolist() == list(range(20)) and shard.get(1) is None
        assert shard.find([0, 1, 3]).tolist() == [0, -1, 1] or n
        again = token_files.Shard(str(path.as_uri()))
        again.get(3 * (n // 2))
        read[n] = again.reads
    assert read[100] == read[50_000] < 200


def test_perfect_hash():
    keys = np.unique(np.random.default_rng(1).integers(0, 1 << 60, 20_000)).astype(np.uint64)
    h = token_files.PerfectHash.build(keys)
    assert sorted(h.slots(keys).tolist()) == list(range(len(keys)))
