import hashlib
import re
import zlib
from collections import Counter, defaultdict

from pyspark.sql import functions as F

from mvspark.llm import decontaminate, exact_dedup, sharding
from mvspark.llm.common import components


def norm(t):
    return re.sub(r"[\x20\x09-\x0D]", "", t or "")


def test_exact_duplicates(edge, edge_rows):
    groups = defaultdict(list)
    for i, t in edge_rows:
        groups[norm(t)].append((-len(t or ""), i is None, i or 0, i))
    want = Counter()
    for i, t in edge_rows:
        g = groups[norm(t)]
        keep = min(g)[3]
        want[i, keep, len(g), i == keep, hashlib.sha256(norm(t).encode()).hexdigest()] += 1
    for fan_in in (2, 16):
        assert Counter(map(tuple, exact_dedup.exact_duplicates(edge, fan_in).collect())) == want
    kept = exact_dedup.drop_exact_duplicates(edge)
    assert kept.columns == edge.columns
    texts = {norm(t) for _, t in edge_rows}
    assert {norm(r.text) for r in kept.collect()} == texts
    assert (40, "other text") in {(r.doc_id, r.text) for r in kept.collect()}


def test_empty_tables(spark, empty):
    assert exact_dedup.exact_duplicates(empty).count() == 0
    bench = spark.createDataFrame([], "item_id long, text string")
    assert decontaminate.contamination(empty, bench).count() == 0
    assert sharding.reshard(empty, F.lit(0)).count() == 0


def brute_contamination(rows, bench, window=10):
    word = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")

    def w(t):
        return word.findall(re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))

    out = Counter()
    for i, t in rows:
        d, hit, items = w(t), set(), set()
        for k, b in bench:
            b = w(b)
            n = min(window, len(b))
            pats = {tuple(b[j : j + n]) for j in range(len(b) - n + 1)} if n else ()
            for j in range(len(d) - n + 1 if n else 0):
                if tuple(d[j : j + n]) in pats and k is not None:
                    hit.update(range(j, j + n))
                    items.add(str(k))
        out[i, len(d), len(hit), len(items), hashlib.sha256(",".join(sorted(items)).encode()).hexdigest(), bool(hit)] += 1
    return out


def test_decontamination(spark, edge, edge_rows):
    rows = [t for _, t in edge_rows]
    bench = [(1, rows[6]), (2, " ".join(rows[7].split()[100:118]).upper()), (10, rows[3]), (11, None), (12, "..."), (13, rows[1]), (14, rows[6]), (None, rows[7])]
    table = spark.createDataFrame(bench, "item_id long, text string")
    want = brute_contamination(edge_rows, bench)
    for block in (5, 10**6):
        got = decontaminate.contamination(edge, table, block_words=block).drop("spans", "items")
        assert Counter(map(tuple, got.collect())) == want
        clean = decontaminate.drop_contaminated(edge, table, block_words=block)
        assert clean.columns == edge.columns and clean.count() == sum(n for k, n in want.items() if not k[-1])


def test_resharding(edge, edge_rows):
    old = F.pmod(F.xxhash64("source", "doc_id"), F.lit(3))
    got = sharding.reshard(edge, old, n_old=3, n_new=4, blocks=5).collect()
    assert Counter((r.doc_id, r.size, r.text_crc32) for r in got) == Counter(
        (i, len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for i, t in edge_rows
    )
    total, load, slots = sum(r["size"] for r in got), Counter(), defaultdict(list)
    for r in got:
        load[r.shard] += r["size"]
        slots[r.shard].append(r.slot)
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    assert max(load.values()) - total / 4 <= 60_001
    assert all(r.moved == (r.shard != r.old_shard) for r in got)


def test_rewrite_touches_affected_shards_only(spark, tmp_path):
    text = lambda i: "x" * (i * 7 % 90)
    rows = [(i, text(i), i % 4, "a", 9) for i in range(800)] + [(5, text(5), 1, "a", 9)] * 3 + [(None, None, 1, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, old int, own string, shard int")
    lay = sharding.layout(docs, F.when(docs["old"] < 2, 1).otherwise(docs["old"])).persist()
    supply = Counter()
    for r in lay.collect():
        supply[r.old_shard] += r["size"]
    # capacities that shards 2 and 3 fill exactly stay as they are
    place = sharding.place(lay, 4, 8).persist()
    out, touched = sharding.rewrite(lay, place, f"file://{tmp_path}/new")
    got = out.collect()
    assert Counter(tuple(r.row) for r in got) == Counter(rows)
    files = {int(p.name[6:]) for p in (tmp_path / "new").glob("shard=*")}
    assert files == {r.shard for r in got} <= set(touched) | {r.shard for r in got}
    moved = sum(len(r.row.text or "") + 1 for r in got if r.shard != r.old_shard)
    total = sum(supply.values())
    demand = [total * (j + 1) // 8 - total * j // 8 for j in range(8)]
    fewest = total - sum(min(supply[j], demand[j]) for j in range(8))  # what any plan with these capacities must move
    assert abs(moved - fewest) <= 8 * 91
    slots = defaultdict(list)
    for r in got:
        slots[r.shard].append(r.slot)
    assert all(sorted(x) == list(range(len(x))) for x in slots.values())


def test_untouched_shards_keep_their_files(spark, tmp_path):
    docs = spark.createDataFrame([(i, "abc", i % 2) for i in range(64)], "doc_id long, text string, old int")
    lay = sharding.layout(docs, docs["old"], blocks=4)
    same = sharding.place(lay, 2, 2)
    out, touched = sharding.rewrite(lay, same, f"file://{tmp_path}/new")
    assert touched == [] and out.count() == 64 and out.where("shard <> old_shard").count() == 0


def test_flow_is_cheapest():
    cost = [[3, 1, 4], [2, 5, 9]]
    flow = sharding.min_cost_flow([5, 4], [3, 3, 3], lambda i, j: cost[i][j])
    best = min(
        cost[0][0] * a + cost[0][1] * b + cost[0][2] * (5 - a - b) + cost[1][0] * (3 - a) + cost[1][1] * (3 - b) + cost[1][2] * (a + b - 2)
        for a in range(4) for b in range(4) if 2 <= a + b <= 5
    )
    assert sum(cost[i][j] * f for (i, j), f in flow.items()) == best


def test_components(spark):
    import random

    r = random.Random(1)
    pairs = [(r.randrange(300), r.randrange(300)) for _ in range(160)] + [(i, i + 1) for i in range(1000, 1040)] + [(2000, 2000 + i) for i in range(1, 50)]
    root = {v: v for p in pairs for v in p}

    def find(v):
        while root[v] != v:
            v = root[v]
        return v

    for a, b in pairs:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    want = {v: find(v) for p in pairs if p[0] != p[1] for v in p}
    got = components(spark.createDataFrame(pairs, "a long, b long")).collect()
    assert {x.v: x.root for x in got} == want and len(got) == len(want)
