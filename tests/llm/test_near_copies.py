"""Near copies of whole texts against brute force, and planted ones through the pipeline's stage."""

import random
from collections import defaultdict

import pytest

import corpus_pipeline
from mvspark.llm import near_copies

from .conftest import frame
from .test_models import classes


def plain_set(text):
    w = (text or "").encode().lower().split()
    return frozenset(tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))) if len(w) >= 5 else frozenset([tuple(w)])


def alike(a, b):
    return 9 * len(a & b) >= 4 * (len(a) + len(b))


def planted():
    r = random.Random(8)
    word = [f"w{i}" for i in range(2000)]
    common = " ".join(r.choice(word) for _ in range(12))
    rows, i = [], 0
    for n in (7, 12, 40, 90, 300, 1200):
        for _ in range(6):
            base = [r.choice(word) for _ in range(n)] + (common.split() if n < 50 else [])
            for share in (0, 0.01, 0.02, 0.03, 0.045, 0.08):
                t = list(base)
                for k in r.sample(range(n), round(share * n)):
                    t[k] = r.choice(word)
                rows.append((i, " ".join(t)))
                i += 1
    crowd = [r.choice(word) for _ in range(120)]
    for _ in range(60):
        t = list(crowd)
        for k in r.sample(range(120), 3):
            t[k] = r.choice(word)
        rows.append((i, " ".join(t)))
        i += 1
    r.shuffle(rows)
    return rows


@pytest.mark.parametrize("drawn", [1, 2])
def test_near_copies_find_all_pairs(spark, edge_rows, drawn):
    rows = planted() + [(None if i is None else i + 10_000, t) for i, t in edge_rows]
    sets = {plain_set(t) for _, t in rows}
    number = {s: k for k, s in enumerate(sorted(sets, key=sorted))}
    by = {k: s for s, k in number.items()}
    root = classes(set(by), lambda a, b: alike(by[a], by[b]))
    low = {}
    for i, t in rows:
        if i is not None:
            c = root[number[plain_set(t)]]
            low[c] = min(low.get(c, i), i)
    got = near_copies.near_copies(frame(spark, rows).repartition(4), drawn).collect()
    want = sorted(((i, low.get(root[number[plain_set(t)]])) for i, t in rows), key=str)
    assert sorted(((x.doc_id, x.component_id) for x in got), key=str) == want


def test_pipeline_stage_drops_planted_near_copies(spark, empty):
    rows = planted()
    stage = corpus_pipeline.STAGES[2][1]
    docs = frame(spark, rows)
    kept = stage(spark, docs, "")
    assert kept.columns == docs.columns
    text = dict(rows)
    left = sorted(x.doc_id for x in kept.collect())
    sets = {i: plain_set(text[i]) for i in text}
    assert not [(a, b) for k, a in enumerate(left) for b in left[k + 1 :] if alike(sets[a], sets[b])]
    groups = defaultdict(list)
    for i, c in classes(list(sets), lambda a, b: alike(sets[a], sets[b])).items():
        groups[c].append(i)
    assert left == sorted(min(g) for g in groups.values())
    assert stage(spark, empty, "").count() == 0
