"""Near-duplicates, URL filters, language model, toxicity, passages and the pipeline against brute force."""

import math
import os
import random
import re
from collections import Counter

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from mvspark.llm import lm_score, paragraph_dedup, simhash, toxicity, url_filter

from .conftest import frame

SF1 = "/root/testdata/sf0.1"


def classes(items, linked):
    root = {i: i for i in items}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    items = sorted(items)
    for i, a in enumerate(items):
        for b in items[i + 1 :]:
            if linked(a, b):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {i: find(i) for i in items}


# --- near-duplicates ---


def plain_fingerprint(text):
    t = re.sub("[A-Z]", lambda m: m[0].lower(), text or "")
    w = re.findall(r"[^\x20\x09-\x0D]+", t)
    sh = [" ".join(w[i : i + 3]) for i in range(max(1, len(w) - 2))] if w else []
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in sh]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h)) if h else 0


def test_near_duplicates(edge, edge_rows, empty):
    fp = {(i, t): plain_fingerprint(t) for i, t in edge_rows}
    root = classes(set(fp.values()), lambda a, b: (a ^ b).bit_count() <= 2)
    low: dict = {}
    for (i, _), f in fp.items():
        if i is not None:
            low[root[f]] = min(low.get(root[f], i), i)
    got = simhash.near_duplicates(edge).collect()
    assert Counter((r.doc_id, r.fingerprint, r.component_id) for r in got) == Counter(
        (i, f"{fp[i, t]:016x}", low.get(root[fp[i, t]])) for i, t in edge_rows
    )
    assert simhash.near_duplicates(empty).count() == 0
    kept = simhash.drop_near_duplicates(edge)
    assert kept.columns == edge.columns
    assert {r.doc_id for r in kept.collect()} <= set(low.values()) | {None}


@pytest.mark.parametrize("dense", [-10_000, 10, 10**9])
def test_links_find_all_pairs(spark, dense):
    r = random.Random(4)
    fps = {r.getrandbits(64) for _ in range(150)}
    for c in list(fps)[:12]:
        for _ in range(25):
            x = c
            for _ in range(r.randint(1, 4)):
                x ^= 1 << r.randrange(64)
            fps.add(x)
    signed = lambda x: x - (1 << 64) if x >> 63 else x
    want = classes({signed(x) for x in fps}, lambda a, b: ((a ^ b) & (1 << 64) - 1).bit_count() <= 2)
    g = spark.createDataFrame([(signed(x), 0) for x in fps], "fp long, low long")
    edges = [(e.a, e.b) for e in simhash.links(g, sketch=8, dense=dense).collect()]
    assert all(((a ^ b) & (1 << 64) - 1).bit_count() <= 2 for a, b in edges)
    linked = {frozenset(e) for e in edges}
    assert classes({signed(x) for x in fps}, lambda a, b: frozenset((a, b)) in linked) == want


def test_thresholds_are_cheapest():
    r = np.random.default_rng(2)
    costs = np.concatenate([np.zeros((40, 3, 1)), np.cumsum(r.uniform(0, 9, (40, 3, 3)), axis=2)], axis=2)
    chosen, cost = simhash.allocate(costs, 0)
    for n in range(40):
        best = min(costs[n, 0, a + 1] + costs[n, 1, b + 1] + costs[n, 2, -a - b + 1] for a in range(-1, 3) for b in range(-1, 3) if -1 <= -a - b <= 2)
        assert cost[n] == pytest.approx(best) and chosen[n].sum() == 0


# --- URL filters ---


def test_urls(spark):
    urls = [None, "", "no scheme", "http://A.Example.NET/en/1?x=/y", "https://x.net", "http://net/", "http://b.example.com/de/7#z", "http://org/fr/", "http://notnet/de/",
            "http://sub.example.org/fr/a", "http://u@h:80/p?q", "a://b://c/d", "http://h?x", "http://h#y", "http://example.net/en", "HTTP://x.COM/\n/q"]
    urls += [f"http://shop.example.com/de/{i}" for i in range(40)] + [f"http://shop.example.com/es/{i}.html" for i in range(40)] + ["http://shop.example.com/de"]
    df = spark.createDataFrame([(i, u, "h", 1, "t") for i, u in enumerate(urls)], "page_id long, url string, host string, n int, template string")
    got = {r.page_id: r for r in url_filter.judge(df).collect()}
    assert len(got) == len(urls)
    for i, u in enumerate(urls):
        m = re.match(r"(?s)(?:.*?)://([^/?#]*)([^?#]*)", u or "")
        host, path = (re.sub("[A-Z]", lambda c: c[0].lower(), m[1]), m[2]) if m else ("", "")
        fits = [(len(h + p), h + p, v) for v, h, p in url_filter.RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
        assert (got[i].host, got[i].path) == (host, path)
        assert got[i].rule == (max(fits)[1] if fits else None)
        if fits:
            assert got[i].verdict == max(fits)[2]
        assert got[i].verdict in ("allow", "block")
    assert all(r.verdict == "allow" for r in got.values() if "/es/" in r.path)
    assert url_filter.judge(df.limit(0)).count() == 0


def test_like_branches_merge(spark):
    rows = [("h", f"/{s}/x{i}", int(i < bad)) for s, n, bad in (("a", 10, 1), ("b", 10, 2), ("d", 6000, 600), ("c", 40, 40)) for i in range(n)]
    rows += [("h", f"/{s}/x{i}", None) for s in ("u", "v") for i in range(20)]
    pages = spark.createDataFrame(rows, "host string, path string, bad int")
    tree = url_filter.templates(pages, F.col("bad")).select(F.get("shape", 0).alias("s"), "template", "share").distinct().collect()
    branch = {r.s: r.template.split("/")[1] for r in tree}
    assert branch["a"] == branch["b"] == branch["d"] == "~a" and branch["c"] == "c" and branch["u"] == branch["v"] == "~u"
    assert all((r.share >= url_filter.REJECT) == (r.s == "c") for r in tree)


def plain_judge(urls, rules):
    """Verdicts of the tree, host by host and branch by branch."""
    def classed(x):
        if re.fullmatch(r"[0-9]{4}-[0-9]{2}(-[0-9]{2})?", x):
            return "{date}"
        if re.fullmatch("[0-9]+", x):
            return "{n}"
        if m := re.fullmatch(r"[0-9]+\.([A-Za-z]{1,5})", x):
            return "{n}." + m[1]
        return "{hex}" if re.fullmatch("[0-9A-Fa-f-]{8,}", x) else x

    pages, out = [], {}
    for i, u in urls:
        m = re.match(r"(?s)(?:.*?)://([^/?#]*)([^?#]*)", u or "")
        host, path = (m[1].lower(), m[2]) if m else ("", "")
        fits = [(len(h + p), v) for v, h, p in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
        label = int(max(fits)[1] == "block") if fits else None
        segs = [classed(x) for x in path.split("/") if x]
        if len(segs) > url_filter.DEPTH:
            segs = [*segs[: url_filter.DEPTH], "{more}" + "/".join(segs[url_filter.DEPTH :])]
        pages.append((i, host, tuple(segs), label, [""]))
        out[i] = label

    def count(some):
        known = [p[3] for p in some if p[3] is not None]
        return len(some), len(known), sum(known)

    def split(some, level):
        kids = {}
        for p in some:
            if len(p[2]) > level:
                kids.setdefault(p[2][level], []).append(p)
        named, groups, name = {}, {}, {}
        for seg, mine in kids.items():
            below = "|".join(sorted({"" if len(p[2]) <= level + 1 else p[2][level + 1] if p[2][level + 1].startswith("{") else "w" for p in mine}))
            if len(mine) < url_filter.SUPPORT and not seg.startswith("{"):
                name[seg] = "*"
            else:
                named.setdefault(below, []).append(seg)
        for below, segs in named.items():
            _, known, bad = (sum(c) for c in zip(*(count(kids[s]) for s in segs)))
            common = (bad + 0.5) / (known + 1)
            for s in segs:
                _, k, b = count(kids[s])
                rate = -2 if not k else -1 if abs(b - k * common) / math.sqrt(k * common * (1 - common)) <= url_filter.ALIKE else int((b + 0.5) / (k + 1) * url_filter.BINS)
                groups.setdefault((below, rate), []).append(s)
        for segs in groups.values():
            for s in segs:
                name[s] = "~" + min(segs) if len(segs) > 1 else s
        for seg, mine in kids.items():
            for p in mine:
                p[4][0] += "/" + name[seg]
        for branch in {p[4][0] for p in some if len(p[2]) > level}:
            split([p for p in some if p[4][0] == branch], level + 1)

    hosts = {}
    for p in pages:
        hosts.setdefault(p[1], []).append(p)
    _, known, bad = count(pages)
    prior = bad / known if known else 0
    verdict = {}
    for some in hosts.values():
        split(some, 0)
        _, known, bad = count(some)
        share = (bad + url_filter.SMOOTH * prior) / (known + url_filter.SMOOTH)
        for template in {p[4][0] for p in some}:
            mine = [p for p in some if p[4][0] == template]
            _, known, bad = count(mine)
            purity = (bad + url_filter.SMOOTH * share) / (known + url_filter.SMOOTH)
            for p in mine:
                verdict[p[0]] = ("block" if (known and purity >= url_filter.REJECT if p[3] is None else p[3]) else "allow", template, round(purity, 9))
    return verdict


def test_verdicts_against_brute_force(spark, sf):
    r = random.Random(2)
    rules = (*url_filter.RULES, ("block", "shop.test", "/promo/1"), ("allow", "shop.test", "/item/"))
    urls = [(x.page_id, x.url) for x in spark.read.parquet(f"{sf}/pages.parquet").collect()]
    urls += [(10_000 + i, f"http://shop.test/promo/{r.randrange(10, 200)}{r.choice(['', '/x'])}") for i in range(200)]
    urls += [(20_000 + i, f"http://shop.test/item/{r.randrange(9)}/{r.choice('abcdefgh')}") for i in range(150)]
    urls += [(30_000 + i, f"https://deep.test{'/s' * r.randrange(28, 40)}/{r.choice(['a', 'b', '7'])}") for i in range(60)]
    urls += [(40_000 + i, u) for i, u in enumerate([None, "", "x", "http://shop.test/promo/19", "http://shop.test/promo/19", "http://tie.test/a/b", "http://tie.test/a/b"])]
    df = spark.createDataFrame([(i, u, "h", "t") for i, u in urls], "page_id long, url string, host string, template string")
    want = plain_judge(urls, rules)
    got = {x.page_id: (x.verdict, x.template, round(x.share, 9)) for x in url_filter.judge(df, rules).collect()}
    assert got == want
    free = {i for i, v in want.items() if v[0] == "block" and "/promo/" in dict(urls)[i] and "/promo/1" not in dict(urls)[i]}
    assert len(free) > 50  # pages that no rule fits, blocked by their template


def test_spread_join(spark):
    from mvspark.llm import common

    many = spark.createDataFrame([(k, i) for k, n in ((1, 5000), (2, 30), (None, 10), (3, 1)) for i in range(n)], "k long, i long")
    one = spark.createDataFrame([(1, "a", 5000), (2, "b", 30), (4, "d", 0)], "k long, v string, n long")
    got = common.spread_join(many, one, ["k"], "n", "left")
    want = many.join(one, ["k"], "left")
    assert got.exceptAll(want.select(got.columns)).count() == 0 and got.count() == want.count()
    assert common.spread_join(many, one.limit(0), ["k"], "n").count() == 0


# --- language model ---


def test_lm_base_and_whole(edge, edge_rows, empty):
    import zlib

    out = lambda i: zlib.crc32(str("" if i is None else i).encode()) % 5 == 1
    w, end = split, b"\n"
    c = Counter()
    for i, t in edge_rows:
        if not out(i):
            c.update([*w(t), end])
    n, v = sum(c.values()), len(c)
    for listed in (0, 10, 10**5):
        got = lm_score.scores(edge, listed).collect()
        mine = Counter((r.doc_id, r.held_out, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 6)) for r in got)
        assert mine == Counter(
            (i, out(i), len(w(t)) + 1, sum(c[x] > 0 for x in [*w(t), end]), n,
             round(sum(math.log10((c[x] + 0.5) / (n + 0.5 * (v + 1))) for x in [*w(t), end]), 6)) for i, t in edge_rows
        )
        assert all(math.isfinite(r.score) and r.score < 0 for r in got)
    again = Counter((r.doc_id, r.score) for r in lm_score.scores(edge, 10**5).collect())
    assert again == Counter((r.doc_id, r.score) for r in got)
    assert lm_score.scores(empty).count() == 0
    assert lm_score.scores(edge.where(lm_score.held_out(edge["doc_id"]))).where("train_tokens = 0 and n_known = 0 and score < 0").count() > 0


def split(t):
    return (t or "").encode().lower().split()


@pytest.fixture(scope="module")
def lm(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    table = lm_score.word_counts(docs)
    seen = docs.where(~lm_score.held_out(docs["doc_id"])).count()
    n = table.where("kind = 0").agg(F.sum("c")).first()[0] + seen
    texts = [split(r.text) for r in docs.orderBy("doc_id").limit(60).collect()]
    return lm_score.train(docs, table, n, seen, 3000), [t for t in texts if t]


def batch(texts):
    return lm_score.Texts.of([b" ".join(t) for t in texts])


def test_texts_are_cut_and_named_as_whole_words(edge_rows):
    texts = [t or "" for _, t in edge_rows] + ["x", " Ab aB\x0bAB ", "\x1c a\x85b"]
    t = lm_score.Texts.of([x.encode() for x in texts])
    at, names = 0, {}
    for i, x in enumerate(texts):
        w = split(x)
        assert t.first[i] == at and t.words[i] == len(w) and t.is_end[at + len(w)] and t.bytes[i] == sum(map(len, w)) + len(w) + 1
        assert t.word(np.arange(at, at + len(w))) == w
        for word, name in zip(w, t.ids[at : at + len(w)].tolist()):
            assert names.setdefault(word, name) == name
        at += len(w) + 1
    assert len(set(names.values())) == len(names)
    import pyarrow as pa

    old, lm_score.BYTES = lm_score.BYTES, 50
    parts = list(lm_score.text_batches(pa.array(["skip", *texts]).slice(1)))
    lm_score.BYTES = old
    assert [k for s, _ in parts for k in range(s.start, s.stop)] == list(range(len(texts)))
    assert np.concatenate([p.ids for _, p in parts]).tolist() == t.ids.tolist()
    known = np.array([v for k, v in names.items() if len(k) % 2], np.uint64)
    at = lm_score.Places(known)
    leaf = at(t)
    want = {int(v): i for i, v in enumerate(known)}
    assert leaf.tolist() == [at.end if e else want.get(v, at.escape) for v, e in zip(t.ids.tolist(), t.is_end.tolist())]


def test_lm_words_are_a_distribution(lm):
    model, texts = lm
    for t in texts[:4]:
        one = batch([t[:6]])
        k, n = len(one.ids) - 1, len(model.counts)
        leaves, names = np.tile(model.at(one), (n, 1)), np.tile(one.ids, (n, 1))
        leaves[:, k] = np.arange(n)
        topic = np.tile(lm_score.topics(model.at(one), one.first, model.at.escape), n)
        steps = lm_score.Steps(model.tree, leaves.ravel(), names.ravel(), np.arange(n) * (k + 1), topic, model.power, model.entries)
        x, gate, bit, token, _ = steps.inputs(model.table, model.about)
        z = lm_score.logit(x, gate, model.weights)
        p = (1 / (1 + np.exp(-z)) + model.refined[lm_score.level_of(z)]) / 2
        mine = token % (k + 1) == k
        logs = np.bincount(token[mine] // (k + 1), np.log(np.where(bit == 1, p, 1 - p))[mine], n)
        walked = np.zeros(n, bool)
        walked[steps.walks[steps.walks % (k + 1) == k] // (k + 1)] = True
        p = np.exp(logs + np.where(walked, model.tree.rest * math.log(10), 0))
        if len(steps.asked):  # what the first bit rules out is not walked to, and its place in the tree stays empty
            assert 0.3 < p.sum() <= 1 + 1e-6
        else:
            assert p.sum() == pytest.approx(1, abs=1e-6)


def test_lm_spelling_is_a_distribution(lm):
    model, _ = lm
    some = [bytes([a]) for a in range(256) if a not in b" \n\t\r\x0b\x0c"] + [bytes([a, b]) for a in range(97, 123) for b in range(97, 123)]
    p = 10 ** model.spell(some, np.zeros(len(some), np.int64))
    assert 0 < p.sum() <= 1 + 1e-6


def plain_score(model, text, span):
    """The words' part of one text, bit by bit."""
    one = batch([text])
    leaf = model.at(one)
    topic = lm_score.topics(leaf, one.first, model.at.escape)
    last, two = lm_score.context_names(one.ids, one.first)
    own, hit, seen = np.zeros((lm_score.FOLLOWED, 3)), model.refined * lm_score.FIRM, np.full(lm_score.STEPS, lm_score.FIRM)
    total, wait, border = 0.0, [], span

    def code(bit, x, gate, state):
        nonlocal total
        s = max(-14, min(14, float(x @ model.weights[gate]) + float(x @ own[state])))
        cell = int(np.clip(s * (lm_score.STEPS - 1) / 16 + (lm_score.STEPS - 1) / 2 + 0.5, 0, lm_score.STEPS - 1))
        p = 1 / (1 + math.exp(-s))
        q = min(max((p + hit[cell] / seen[cell]) / 2, 1e-6), 1 - 1e-6)
        total += math.log10(q if bit else 1 - q)
        wait.append((state, x, bit - p, cell, bit))

    for k, to in enumerate(leaf.tolist()):
        if k == border:
            border = 2 * border + span
            n, slope = Counter(), np.zeros((lm_score.FOLLOWED, 3))
            for state, x, err, cell, bit in wait:
                n[state] += 1
                slope[state] += err * x
                hit[cell] += bit
                seen[cell] += 1
            for state in n:
                own[state] += lm_score.FAST * slope[state] / (1 + n[state] / 256)
            wait.clear()
        slot, check = lm_score.followed(two[k : k + 1], model.power)
        e = model.entries[slot[0]]
        named, times, miss = int(e["value"]), int(e["n"]), int(e["miss"])
        guess = named & ((1 << lm_score.LEAF) - 1)
        if times > 0 and named >> lm_score.LEAF == check[0] and guess < len(model.counts):
            state = 1 + min(times - 1, 2) * 2 + (miss > 0)
            code(int(guess == to), np.array([math.log((times + 0.4) / (miss + 0.4)), 1, 0]), lm_score.SEEN * lm_score.DEEP + state, state)
            if guess == to:
                continue
        for depth in range(model.tree.length[to]):
            at = model.tree.offset[to] + depth
            salt = model.tree.salt(np.arange(at, at + 1))
            odds, often = (float(v[0]) for v in model.table.look(lm_score.slots_of(last[k : k + 1], salt, model.power)))
            with np.errstate(over="ignore"):
                about = (topic[k : k + 1].astype(np.uint64) + np.uint64(7)) * np.uint64(0x94D049BB133111EB)
            tells = float(model.about.look(lm_score.slots_of(about, salt, lm_score.TOPIC_POWER))[0][0])
            code(int(model.tree.bit[at]), np.array([model.tree.odds[at], odds, tells]), min(int(often), lm_score.SEEN - 1) * lm_score.DEEP + depth, 0)
        total += model.tree.rest[to]
    return total


def test_lm_scores_bit_by_bit(lm):
    model, texts = lm
    some = sorted(texts, key=len)[:25]
    got = model.score(batch(some), span=8)[0]
    assert got == pytest.approx([plain_score(model, t, 8) for t in some], rel=1e-4)
    alone = [model.score(batch([t]), span=8)[0][0] for t in some]
    assert got == pytest.approx(alone, rel=1e-6)  # a text's score does not depend on what it is scored with


def test_lm_every_step_is_predicted_from_contexts(lm):
    """No step of a walk is left to the words' counts alone: all are kept, were counted after their contexts, and are scored by them."""
    model, texts = lm
    parent, _ = lm_score.huffman(model.counts)
    n = len(model.counts)
    for leaf in range(0, n, 7):
        at, depth = leaf, 0
        while at != 2 * n - 2:
            at, depth = parent[at], depth + 1
        assert model.tree.length[leaf] == depth
    assert model.tree.length.max() > 8 and not model.tree.rest.any()
    trained = [t for t in texts if len(t) > 50][0]
    one = batch([trained])
    leaf = model.at(one)
    s = lm_score.Steps(model.tree, leaf, one.ids, one.first, lm_score.topics(leaf, one.first, model.at.escape), model.power)
    deep = s.depth >= 8
    assert deep.sum() > 20 and (model.table.look(s.slots[deep])[1] > 0).mean() > 0.5


def test_lm_order_of_words_counts(lm):
    model, texts = lm
    r = random.Random(3)
    long = [t for t in texts if len(t) > 100][:8]
    mixed = [r.sample(t, len(t)) for t in long]
    assert model.score(batch(long))[0].sum() > model.score(batch(mixed))[0].sum() * 0.9


def test_lm_counts_of_a_pass_and_of_the_model_agree():
    r = np.random.default_rng(2)
    t = lm_score.Counts(10)
    for _ in range(5):
        t.add(r.integers(0, 1 << 10, 3000).astype(np.int32), r.integers(0, 2, 3000))
    t.settle()
    at = np.arange(1 << 10)
    (x, seen), (y, again) = t.look(at), lm_score.Ready(lm_score.packed(t.n)).look(at)
    assert np.abs(x - y).max() < 1 / 2048 and (seen == again).all() and t.n.sum() == 15_000


def test_lm_steps_are_walked_once_for_counting_and_for_asking():
    """What a task learns from is part of what it counts, and what counts say is kept between settlings: nothing is hashed or worked out twice."""
    r = np.random.default_rng(5)
    tree, power = lm_score.Tree(r.integers(1, 99, 40), keep=lm_score.DEEP), 10
    leaf, first = r.integers(0, 40, 900), np.arange(0, 900, 90)
    ids, topic = (leaf + 5).astype(np.uint64), r.integers(0, 4, 900)
    counted = lm_score.Steps(tree, leaf, ids, first, topic, power)
    f, table, about = lm_score.Followers(power), lm_score.Counts(power), lm_score.Counts(lm_score.TOPIC_POWER)
    for _ in range(3):
        f.add(counted.two, leaf)
        for t, slot in ((table, counted.slots), (about, counted.topic_slots)):
            t.add(slot, counted.bit)
            t.settle()
    asked = counted.asking(f)
    assert len(asked.asked) and 0 < len(asked.walks) < len(counted.walks) == 900
    for x, y in zip(asked.inputs(table, about), lm_score.Steps(tree, leaf, ids, first, topic, power, f).inputs(table, about)):
        assert np.array_equal(x, y)
    n = 3 * np.bincount(counted.slots * 2 + counted.bit, minlength=2 << power)
    odds, seen = table.look(np.arange(1 << power))
    assert np.array_equal(table.n, n) and np.array_equal(odds, table.odds(np.arange(1 << power)))
    assert np.allclose(odds, np.log(n[1::2] + 0.4) - np.log(n[::2] + 0.4), atol=1e-5) and (seen[n[::2] + n[1::2] == 0] == 0).all()


def test_lm_learner_moves_weights_by_gate():
    r = np.random.default_rng(6)
    one = lm_score.Learner(np.full((5, 2), 0.3))
    x, gate, bit = [r.normal(size=700).astype(np.float32) for _ in range(2)], r.choice([0, 1, 3], 700).astype(np.int32), r.integers(0, 2, 700).astype(np.int8)
    one.learn(x, gate, bit)
    z = np.stack(x, 1).astype(float)
    p = 1 / (1 + np.exp(-z @ [0.3, 0.3]))
    for g in range(5):
        at = gate == g
        bend = (z[at].T * (p * (1 - p))[at]) @ z[at] + np.eye(2) * lm_score.STEADY
        assert np.allclose(one.w[g], 0.3 + lm_score.RATE * np.linalg.solve(bend, z[at].T @ (bit - p)[at])) and one.mass[g] == at.sum()
    assert one.all.sum() == 700 and one.hit.sum() == bit.sum()


def test_followers_keep_the_most_frequent():
    r = np.random.default_rng(1)
    names, leaf = r.integers(0, 1 << 63, 40, dtype=np.uint64)[r.integers(0, 40, 500)], r.integers(0, 3, 500)
    f = lm_score.Followers(14)
    f.add(names, leaf)
    got = f.entries()
    for x in set(names.tolist()):
        n = Counter(leaf[names == x].tolist())
        slot, check = lm_score.followed(np.array([x], np.uint64), 14)
        e = got[slot[0]]
        top = max(n.values())
        assert e["n"] == top and int(e["value"]) & 3 == min(k for k, c in n.items() if c == top) and int(e["value"]) >> lm_score.LEAF == check[0]
    half = [lm_score.Followers(14) for _ in range(2)]
    for h, part in zip(half, (slice(0, 250), slice(250, 500))):
        h.add(names[part], leaf[part])
    one, other = (lm_score.merged([h.entries() for h in order]) for order in (half, half[::-1]))
    assert (one == other).all()


@pytest.mark.parametrize("where", ["/root/testdata/sf0.01", SF1])
def test_lm_beats_unigrams_on_held_out_texts(spark, where):
    if not os.path.exists(where):
        pytest.skip("needs the tables")
    r = lm_score.scores(spark.read.parquet(f"{where}/documents.parquet")).where("held_out").agg(F.sum("score"), F.sum("base_score")).first()
    assert r[0] > r[1]


# --- toxicity ---


def test_block_max_neighbours_are_exact():
    r = np.random.default_rng(3)
    vectors = []
    for _ in range(500):
        f = r.choice(30, r.integers(1, 6), replace=False)
        x = r.uniform(0.1, 1, len(f))
        vectors.append(dict(zip(f.tolist(), (x / np.linalg.norm(x)).tolist())))
    index = toxicity.BlockMaxIndex(vectors, 30, 16)
    for q in vectors[:60]:
        full = [(-round(sum(w * v.get(f, 0) for f, w in q.items()), 12), i) for i, v in enumerate(vectors)]
        e, s = index.top(q, 7)
        want = sorted(x for x in full if x[0] < 0)[:7]
        assert np.allclose(s, [-x for x, _ in want], atol=1e-9)


def test_toxicity(spark, edge, edge_rows, empty):
    r = random.Random(6)
    say = lambda bad: " ".join(r.choice(["alpha", "beta", "gamma", "delta"]) for _ in range(20)) + (" zorkface" * bad)
    rows = [(1000 + i, say(2 if i % 4 == 0 else 0)) for i in range(400)]
    docs = frame(spark, rows).unionByName(edge)
    labels = spark.createDataFrame([(i, None, int("zork" in t), "x") for i, t in rows] + [(5, 1, None, "y"), (None, 1, 1, "z")], "doc_id long, quality int, toxic int, text string")
    got = toxicity.toxicity(docs, labels).collect()
    assert len(got) == len(rows) + len(edge_rows) and all(0 <= x.score <= 1 and x.predicted == (x.score >= 0.5) for x in got)
    assert all(x.predicted == int((x.doc_id - 1000) % 4 == 0) for x in got if x.doc_id is not None and 1000 <= x.doc_id < 1400)
    flipped = labels.withColumn("toxic", F.when(toxicity.held_out(F.col("doc_id")), 1 - F.col("toxic")).otherwise(F.col("toxic")))
    again = toxicity.toxicity(docs, flipped).collect()
    assert Counter((x.doc_id, x.score) for x in got) == Counter((x.doc_id, x.score) for x in again)
    assert toxicity.toxicity(empty, labels.limit(0)).count() == 0
    assert toxicity.drop_toxic(docs, labels).count() == sum(x.predicted == 0 for x in got)


def test_toxicity_scores_against_brute_force(spark):
    """Scores follow from all examples' cosines, the votes of the nearest and the fitted curve; ties go to the smaller example."""
    r = random.Random(11)
    bad = ["zork", "blarg", "snurf"]
    rows = []
    for i in range(300):
        w = [r.choice(["alpha", "beta", "gamma", "delta"]) for _ in range(15)]
        if i % 3 == 0:
            w += [r.choice(bad) for _ in range(r.randint(1, 3))]
        rows.append((i, " ".join(w)))
    rows += [(1000, rows[0][1]), (1001, rows[0][1].upper()), (1002, ""), (1003, None)]
    docs = frame(spark, rows)
    labels = spark.createDataFrame([(i, int(any(b in (t or "") for b in bad))) for i, t in rows[:300]], "doc_id long, toxic int")
    model = toxicity.train(docs, labels)
    got = {x.doc_id: x.score for x in toxicity.toxicity(docs, labels, model).collect()}
    vectors = []
    for e in range(model.index.n):
        v = np.zeros(len(model.known) + 1)
        for f, by in enumerate(model.index.postings):
            if (p := by.get(e // model.index.block)) is not None and (e % model.index.block) in p[0]:
                v[f] = p[1][list(p[0]).index(e % model.index.block)]
        vectors.append(v)
    for i, t in rows:
        q = model.vector(model.counts(t))
        if not q:
            assert got[i] == pytest.approx(model.blank)
            continue
        s = np.round([sum(w * v[f] for f, w in q.items()) for v in vectors], 12)
        near = np.lexsort((np.arange(len(s)), -s))[: model.k]
        near = near[s[near] > 0]
        mass = s[near] * model.w[near]
        vote = (mass @ model.y[near] + 0.5 * model.blank) / (mass.sum() + 0.5)
        assert got[i] == pytest.approx(toxicity.curve(vote, model.curve), abs=1e-9)
    assert got[1000] == got[1001] == got[0] and got[1002] == got[1003]


# --- passages ---


def test_passages(spark, edge, empty):
    r = random.Random(8)
    word = lambda: "".join(r.choice("abcdefghijklmnop") for _ in range(5))
    line = lambda n: " ".join(word() for _ in range(n))
    same, near, inner = line(60), line(70).split(), line(70)
    docs = {i: [line(30), line(40)] for i in range(30)}
    docs[1].append(same)
    docs[2].insert(0, same.upper())
    docs[3].append(" ".join(near))
    docs[4].append(" ".join(near[:35] + [word()] + near[36:]))
    docs[5].append(f"{line(40)} {inner} {line(30)}")
    docs[6].append(f"{line(20)} {inner} {line(50)}")
    docs[7] += [docs[7][0]]
    rows = [(i, "\n".join(x)) for i, x in docs.items()]
    df = frame(spark, rows)
    docs[8] = [line(10), same[: len(same) // 2], line(5)]
    wrapped = line(52).split()
    rows += [(40, " ".join(wrapped)), (41, "\n".join(" ".join(wrapped[i : i + 7]) for i in range(0, 52, 7))), (42, None), (43, "")]
    df = frame(spark, rows)
    got = {x.doc_id: x for x in paragraph_dedup.repeated_documents(df).collect()}
    assert set(got) == {*range(30), 40, 41, 42, 43}
    assert {i for i, x in got.items() if x.n_paragraphs + x.n_chunks} == {i for i, x in got.items() if x.long_passage} == {1, 2, 3, 4, 5, 6, 40, 41}
    assert got[41].class_id == 40 and got[6].class_id == 5 and got[7].class_id == 7 and got[41].n_chunks > 0 and got[6].chunk_words >= 24
    assert got[2].n_removed == 1 and got[2].keep_ids == [1] and got[4].keep_ids == [3] and got[1].n_removed == 0
    left = {x.doc_id: x.text for x in paragraph_dedup.remove_repeated(df).collect()}
    assert same.upper() not in left[2] and same in left[1] and len(left) == 34
    assert inner in left[5] and inner not in left[6] and left[6].startswith(docs[6][0] + "\n" + docs[6][1]) and left[42] is None
    assert len(set(inner.split()) & set(left[6].split())) <= 2 * (paragraph_dedup.WINDOW - 1)
    assert paragraph_dedup.repeated_documents(empty).count() == 0
    assert paragraph_dedup.repeated_documents(edge).where("doc_id is null").count() == 0


def test_every_run_of_fifty_words_has_a_common_anchor():
    r = random.Random(9)
    word = lambda: "".join(r.choice("abcdef") for _ in range(3))
    for n in (50, 51, 70, 200):
        for _ in range(40):
            run = [word() for _ in range(n)]
            a = [word() for _ in range(r.randrange(80))] + run + [word() for _ in range(r.randrange(80))]
            b = [word() for _ in range(r.randrange(80))] + run + [word() for _ in range(r.randrange(80))]
            t = lm_score.Texts.of([" ".join(a).encode(), b"x y", " ".join(b).encode()])
            text = t.text[~t.is_end]
            at, names = paragraph_dedup.anchors(t.name, text)
            mine = [{x for x, i in zip(names.tolist(), at.tolist()) if text[i] == k} for k in (0, 2)]
            assert mine[0] & mine[1]
            assert all(text[i] == text[i + paragraph_dedup.ANCHOR - 1] for i in at.tolist())


@pytest.mark.parametrize("joined", [0, 40])
def test_large_buckets_lose_no_link(spark, joined):
    r = random.Random(8)
    word = lambda: "".join(r.choice("abcdefgh") for _ in range(4)).encode()
    lines = set()
    for _ in range(6):
        base = [word() for _ in range(r.randint(12, 60))]
        for _ in range(25):
            w = list(base[: r.randint(len(base) * 3 // 4, len(base))])
            for _ in range(r.randint(0, 2)):
                w[r.randrange(len(w))] = word()
            lines.add(b" ".join(w))
    keys = {paragraph_dedup._key(x): paragraph_dedup._shingles(x) for x in sorted(lines)}
    linked = lambda a, b: len(keys[a] & keys[b]) >= 0.8 * len(keys[a] | keys[b])
    want = classes(keys, linked)
    first = classes(sorted(keys)[:joined], linked)
    crowd = spark.createDataFrame([(0, 0, k, len(keys)) for k in keys], "band int, value int, key long, n long")
    bodies = spark.createDataFrame([(paragraph_dedup._key(x), x) for x in lines], "key long, line binary")
    roots = spark.createDataFrame(list(first.items()), "v long, root long")
    edges = [(e.a, e.b) for e in paragraph_dedup.left_over(crowd, bodies, roots).collect()] + list(first.items())
    assert all(want[a] == want[b] for a, b in edges)
    near = {frozenset(e) for e in edges}
    assert classes(keys, lambda a, b: frozenset((a, b)) in near) == want
    assert len(set(want.values())) > 6


def test_passage_classes_against_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(120).collect()
    lines = sorted({b" ".join(x.split()) for d in docs for x in d.text.encode().lower().split(b"\n") if len(x.split()) >= 5})
    sets = {x: paragraph_dedup._shingles(x) for x in lines}
    want = classes(lines, lambda a, b: len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]))
    sizes = Counter(want.values())
    shared = Counter()
    for d in docs:
        for c in {want[y] for y in (b" ".join(x.split()) for x in d.text.encode().lower().split(b"\n")) if y in want}:
            shared[c] += 1
    got = paragraph_dedup.repeated_passages(frame(spark, [(d.doc_id, d.text) for d in docs])).where("place >= 0")
    assert got.select("class_id").distinct().count() == sum(n > 1 for n in shared.values()) and sizes


# --- pipeline ---


def edge_stage(spark, rows):
    """Rows with names that the stages use themselves, null ids, repeated rows and nulls."""
    cols = ["doc_id", "text", "__own", "__id", "__check", "__crc", "own", "row", "id", "check"]
    return spark.createDataFrame([(i, t, "o", 1, "c", 2, "w", "r", 7, "k") for i, t in rows], "doc_id long, text string, __own string, __id long, __check string, __crc long, own string, row string, id long, check string").select(cols)


def test_stages_take_odd_tables(spark, tmp_path):
    pipeline = pytest.importorskip("corpus_pipeline")
    spark.createDataFrame([(1, 0), (None, 1)], "doc_id long, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(1, "a b c d e f g h i j k"), (None, None)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    long = " ".join(f"w{i}" for i in range(40))
    rows = [(None, None), (None, "x"), (1, long), (1, long), (2, long + " "), (3, long.replace("w39", "z")), (4, ""), (5, None), (6, "a b c d e f g h i j k l m n")]
    for name, stage in pipeline.STAGES:
        for some in (rows, []):
            docs = edge_stage(spark, some)
            out = stage(spark, docs, str(tmp_path))
            got = out.collect()
            if name != "packing":
                assert out.columns == docs.columns
                assert {(r.doc_id, r.text) for r in got} <= set(some)
            if not some:
                assert not got
            elif name == "toxicity":
                assert len(got) == len(some)
            elif name == "exact_dedup":
                assert sorted(r.doc_id for r in got if r.text and r.text.startswith("w0")) == [2, 3]  # the longer of equal texts
            elif name == "simhash_dedup":
                assert sorted(r.doc_id for r in got if r.text and r.text.startswith("w0")) == [1, 1]  # rows of one id are one document
            elif name == "decontamination":
                assert 6 not in {r.doc_id for r in got} and len(got) == len(some) - 1


def test_pipeline_against_brute_force(spark, tmp_path):
    """Planted exact and near copies and benchmark passages, each stage worked out apart in plain Python."""
    import hashlib
    from collections import defaultdict

    pipeline = pytest.importorskip("corpus_pipeline")
    r = random.Random(12)
    word = [f"v{i}" for i in range(400)]
    base = [" ".join(r.choice(word) for _ in range(60)) for _ in range(40)]
    item = " ".join(r.choice(word) for _ in range(14))
    texts = list(base) + [t.replace(" ", "  ") for t in base[:6]] + [base[7] + " more", base[8][: -4] + " end"]
    texts += [base[10] + " " + item, item.upper(), None, ""]
    rows = list(enumerate(texts))
    r.shuffle(rows)
    spark.createDataFrame([(i, t, "en", "s", 1) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([], "doc_id long, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    groups = defaultdict(list)
    for i, t in rows:
        groups[re.sub(r"[\x20\x09-\x0D]", "", t or "")].append((-len(t or ""), i))
    kept = {min(g)[1] for g in groups.values()}
    words = {i: (texts[i] or "").lower().split() for i in kept}
    sets = {i: frozenset(zip(*(w[k:] for k in range(5)))) if len(w) >= 5 else frozenset([tuple(w)]) for i, w in words.items()}
    root = classes(kept, lambda a, b: 9 * len(sets[a] & sets[b]) >= 4 * (len(sets[a]) + len(sets[b])))
    kept = set(root.values())
    windows = {tuple(item.split()[k : k + 10]) for k in range(5)}
    kept = {i for i in kept if not windows & set(zip(*(words[i][k:] for k in range(10))))}
    packed = pipeline.run(spark, str(tmp_path)).collect()
    assert {x.doc_id for x in packed} == kept and hashlib.md5  # every one that stays, and no other
    total = sum(x.length for x in packed)
    assert len({x.sequence_id for x in packed}) == -(-total // 1024)


def test_pipeline(spark, sf):
    pipeline = pytest.importorskip("corpus_pipeline")
    docs = first = spark.read.parquet(f"{sf}/documents.parquet")
    counts = [docs.count()]
    for name, stage in pipeline.STAGES[:-1]:
        docs = stage(spark, docs, sf)
        assert docs.columns == first.columns
        counts.append(docs.count())
    assert counts == sorted(counts, reverse=True) and counts[-1] > counts[0] / 2
    packed = pipeline.run(spark, sf)
    assert {r.doc_id for r in packed.select("doc_id").distinct().collect()} == {r.doc_id for r in docs.select("doc_id").collect()}
