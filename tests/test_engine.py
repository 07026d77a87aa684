"""Worked values, invariants and brute-force checks of the similarity engine."""

import glob
import os

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from mvspark.config import IndexConfig, LinkConfig, SearchConfig, SimConfig
from mvspark.functions import kernel
from mvspark.functions import sql as FS
from mvspark.operators import baselines as B
from mvspark.operators import graph as G
from mvspark.operators import index as I
from mvspark.operators import links as L
from mvspark.operators import measures as M
from mvspark.operators import routing as R
from mvspark.operators import similarity as S
from mvspark.plans import catalogue
from mvspark.sources import fixtures as X

RNG = np.random.default_rng(7)


def unit(n, d=16):
    x = RNG.normal(size=(n, d))
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def test_example_and_counterexample():
    q, v, w = catalogue.X_EXAMPLE1
    assert kernel.mv_sim(q, v, weights=w) == pytest.approx(1.8)
    e = np.eye(4)
    assert kernel.edge_weight(e[:2], e) == pytest.approx(0.75)
    assert kernel.edge_weight(e[:2], e, edge_fn="one_sided") == pytest.approx(1.0)
    assert kernel.mv_sim(e[2:3], e[:2]) == 0 and kernel.mv_sim(np.zeros((0, 4)), e) == 0


def test_worked_search_and_metrics():
    q, objs = catalogue.X_EXAMPLE2
    got = [kernel.mv_sim(q, o) for o in objs]
    assert got == pytest.approx([1.85597, 1.69706, 1.30711], abs=1e-5)
    f = lambda i, j: kernel.edge_weight(objs[i], objs[j])
    assert [f(0, 1), f(0, 2), f(1, 2), f(0, 0)] == pytest.approx([0.962963, 0.859808, 0.821751, 1], abs=1e-5)
    assert kernel.softmax(kernel.contribution(q, objs[0])) == pytest.approx([0.469059, 0.530941], abs=1e-5)
    q, v, w = catalogue.X_EXAMPLE1
    assert kernel.mv_sim(q, v, 2, w) == pytest.approx(1.748528, abs=1e-6)
    with pytest.raises(ValueError):
        kernel.similarities(np.eye(2), np.eye(2), "nonsense")
    with pytest.raises(ValueError):
        SimConfig(metric="nonsense")
    kernel.register_metric("half", lambda a, b: np.asarray(a) @ np.asarray(b).T / 2)
    assert kernel.mv_sim(np.eye(2), np.eye(2), metric="half") == 1 and SimConfig(metric="half").metric == "half"
    with pytest.raises(ValueError):
        kernel.register_metric("flat", lambda a, b: np.zeros(3))


def test_block_scores_equal_single_ones():
    for gamma in (1, 2, 5):
        objs = [unit(n) for n in (1, 3, 3, 7, 2, 9)]
        block = kernel.Block(np.concatenate(objs), np.array([len(o) for o in objs]))
        q, w, some = unit(5), RNG.uniform(0, 1, 5), np.array([4, 0, 5, 2])
        assert block.scores(q, some, gamma, w) == pytest.approx([kernel.mv_sim(q, objs[i], gamma, w) for i in some])
        groups = kernel.cluster_tokens(q)
        assert block.clustered_scores(q, groups, some, gamma, w) == pytest.approx([kernel.clustered_sim(q, objs[i], gamma, w, groups=groups) for i in some])
        for kind in kernel.EDGES:
            assert block.edges(3, some, gamma, kind) == pytest.approx([kernel.edge_weight(objs[3], objs[i], gamma, kind) for i in some])
            near = [kernel.edge_weight(objs[3], objs[i], gamma, kind, groups=(kernel.cluster_tokens(objs[3]), kernel.cluster_tokens(objs[i]))) for i in some]
            assert block.edges(3, some, gamma, kind, True) == pytest.approx(near)


def test_settings_are_checked():
    with pytest.raises(ValueError):
        IndexConfig(edge_fn="nonsense")
    with pytest.raises(ValueError):
        SearchConfig(scale=0)
    with pytest.raises(ValueError):
        LinkConfig(how="nonsense")
    with pytest.raises(ValueError):
        SearchConfig(k=10, ef=5)
    with pytest.raises(ValueError):
        SimConfig(gamma=0)
    with pytest.raises(ValueError):
        kernel.mv_sim([[1.0]], [[1.0]], weights=[-1.0])


def test_edge_weight_properties():
    for _ in range(50):
        u, v = unit(RNG.integers(1, 9)), unit(RNG.integers(1, 9))
        f = kernel.edge_weight(u, v)
        assert f == pytest.approx(kernel.edge_weight(v, u)) and -1 - 1e-9 <= f <= 1 + 1e-9
        assert kernel.edge_weight(u, u) == pytest.approx(1)
        assert kernel.edge_weight(np.concatenate([u, u]), v) == pytest.approx(f)
        assert kernel.mv_sim(np.concatenate([u, u]), v) == pytest.approx(2 * kernel.mv_sim(u, v))
        q, bound = unit(4), 2 * 4 * np.sqrt(max(0, 1 - f) * max(len(u), len(v)))
        assert abs(kernel.mv_sim(q, u) - kernel.mv_sim(q, v)) <= bound + 1e-9


def test_clustered_is_below_exact():
    for _ in range(30):
        q, d = unit(9), unit(16)
        exact = kernel.mv_sim(q, d)
        last = -np.inf
        for beta in (2, 4, 8, 16):
            got = kernel.clustered_sim(q, d, beta=beta)
            assert got <= exact + 1e-9 and got >= last - 1e-9
            last = got
        assert last == pytest.approx(exact)
        assert kernel.contribution(q, d, 3).sum() == pytest.approx(3 * kernel.mv_sim(q, d, 3))


def test_lazy_pops_equal_scan():
    for _ in range(40):
        q, v, m = unit(5), unit(6), 4
        lists = {t: sorted(((float(RNG.uniform(0, 1)), int(n)) for n in RNG.choice(30, 5, replace=False)), key=lambda x: (-x[0], x[1])) for t in range(6)}
        rel = kernel.softmax(kernel.contribution(q, v))
        best: dict = {}
        for t, l in lists.items():
            for key, n in l:
                best[n] = max(best.get(n, -1), rel[t] * key)
        want = sorted(best, key=lambda n: (-best[n], n))[:m]
        assert G.linked_nodes(q, v, np.ones(5), 1, lists, m)[0] == want
        flat = [(t, n, key) for t, l in lists.items() for key, n in l]
        links = tuple(np.array(c) for c in zip(*flat))
        assert G.best_linked(q, v, np.ones(5), 1, links, m)[0] == want
        assert G.best_linked(q, v, np.ones(5), 1, links, m, False)[0] == G.linked_nodes(q, v, np.ones(5), 1, lists, m, False)[0]


@pytest.fixture(scope="module")
def words(spark, sf):
    t = X.from_documents(spark, sf, 12, 128).select("mv_id", "tok_ix", "vec").cache()
    q = X.as_queries(X.from_documents(spark, sf, 12, 128, skip=12), 20).cache()
    return t, q, S.objects(t).cache()


def test_scan_equals_brute_force(words):
    t, q, o = words
    objs = {r.mv_id: np.array(r.vecs) for r in o.collect()}
    for gamma in (1, 3):
        got = S.linear_scan(q, o, 5, gamma).collect()
        for qid, m, _ in S.query_block(q):
            want = sorted(((-kernel.mv_sim(m, v, gamma), i) for i, v in objs.items()))[:5]
            mine = sorted((r.rank, r.mv_id, r.score) for r in got if r.qid == qid)
            assert [i for _, i, _ in mine] == [i for _, i in want]
    assert S.linear_scan(q, o, 5, where=F.col("mv_id") < 50).where("mv_id >= 50").count() == 0


def test_graph_search(words):
    t, q, o = words
    truth = S.linear_scan(q, o, 10).cache()
    links = L.build_links(t, 8).cache()
    for trim, shards in (("one_sided", 1), ("mirror", 1), ("one_sided", 3)):
        cfg = IndexConfig(M=8, ef_construction=32, trim=trim, n_shards=shards)
        g = G.build_graph(o, cfg).cache()
        assert {r.rule: r.violations for r in G.check_graph(g, 8).collect()} == dict.fromkeys(["degree", "self", "nesting", "endpoint", "entry"], 0)
        mean = {}
        for linked in (True, False):
            r, st = G.search_graph(q, o, g, SearchConfig(k=10, ef=24, linked=linked), cfg, links if linked else None)
            mean[linked] = M.recall(r, truth, 10).agg(F.avg("recall")).first()[0]
            assert st.count() > 0
        assert mean[True] >= mean[False] - 0.02
        r, _ = G.search_graph(q, o, g, SearchConfig(k=10, ef=10_000), cfg, links)
        assert M.recall(r, truth, 10).agg(F.avg("recall")).first()[0] >= 0.99
    assert L.unsorted_links(links).count() == 0


def test_cells_find_equal_words(words):
    t, _, _ = words
    cells = t.select("mv_id", "tok_ix", F.xxhash64("vec").alias("cell"))
    near = L.token_neighbours(t, 5, cells)
    assert near.where("s <> 128 or mv_id = other_mv").count() == 0


def test_entry_and_twins(spark, sf):
    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", ["k6a_maxsim_topk", "k8_edge_weight", "l7_priority", "b3_floor", "i12_bulk_topm", "c3_refine", "t_state_objects", "r_asof"])
def test_oracle(spark, sf, name):
    con = duckdb.connect()
    for f in glob.glob(f"{sf}/*.parquet"):
        con.sql(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    want = con.sql(entry.oracle_sql()[name])
    got = entry.queries()[name](spark, sf)
    cols = sorted(got.columns)
    assert cols == sorted(want.columns)
    key = lambda r: tuple("" if x is None else f"{x:.9g}" if isinstance(x, float) else str(x) for x in r)
    assert sorted(map(key, got.select(cols).collect())) == sorted(map(key, want.select(", ".join(cols)).fetchall()))


def test_graph_files_round_trip(spark, words, tmp_path):
    _, _, o = words
    cfg = IndexConfig(M=6, ef_construction=16, n_shards=2)
    g = G.build_graph(o, cfg).cache()
    G.save(g, cfg, f"file://{tmp_path}/index")
    back, cfg2 = G.load(spark, f"file://{tmp_path}/index")
    assert cfg2 == cfg
    cols = ["shard", "layer", "mv_id", "top_layer", "nbrs", "weights", "entry"]
    assert g.select(cols).exceptAll(back.select(cols)).count() == 0 and g.count() == back.count()


def test_append_equals_one_build(words):
    _, _, o = words
    cfg, cols = IndexConfig(M=6, ef_construction=16), ["layer", "mv_id", "nbrs", "entry"]
    mid = sorted(r.mv_id for r in o.select("mv_id").collect())[100]
    old = o.where(F.col("mv_id") < mid)
    grown = G.append(G.build_graph(old, cfg), old, o.where(F.col("mv_id") >= mid), cfg).select(cols)
    assert G.build_graph(o, cfg).select(cols).exceptAll(grown).count() == 0
    left = G.delete(G.build_graph(o, cfg), o.where("mv_id % 2 = 0").select("mv_id"))
    assert {r.rule: r.violations for r in G.check_graph(left, 6).collect()} == dict.fromkeys(["degree", "self", "nesting", "endpoint", "entry"], 0)
    assert left.where("mv_id % 2 = 0").count() == 0


def test_sizes_are_checked(words):
    t, q, o = words
    with pytest.raises(ValueError):
        S.query_block(q, limit=10)
    assert S.linear_scan(q.limit(0), o, 5).count() == 0


def _small(spark, n=60, c=4, d=16):
    rows = [(i, j, v.tolist()) for i in range(n) for j, v in enumerate(unit(c, d))]
    return spark.createDataFrame(rows, "mv_id long, tok_ix int, vec array<double>")


def test_routed_search_of_all_shards_is_the_scan(spark):
    t = _small(spark).persist()
    q, o, cfg = X.as_queries(t, 6), S.objects(t).persist(), IndexConfig(M=8, ef_construction=32, n_shards=3)
    centres = R.fit_centres(o, 3)
    routed = R.route_objects(o, centres).persist()
    g, truth = G.build_graph(routed, cfg), S.linear_scan(q, o, 5)
    rows = lambda df: {(r.qid, r["rank"], r.mv_id) for r in df.collect()}
    full, stats = R.search_routed(q, routed, g, centres, SearchConfig(k=5, ef=60, linked=False), cfg)
    assert rows(full) == rows(truth)
    some, less = R.search_routed(q, routed, g, centres, SearchConfig(k=5, ef=60, linked=False, probe_shards=1), cfg)
    assert some.count() <= full.count()
    assert sum(r.scored for r in less.collect()) < sum(r.scored for r in stats.collect()) == 60 * 10
    assert R.fit_centres(o.limit(0), 3).size == 0


def test_search_by_rounds(spark):
    t = _small(spark).persist()
    q, o = X.as_queries(t, 6), S.objects(t).persist()
    ring = spark.createDataFrame([(i, (i + s) % 60) for i in range(60) for s in (1, 7, 53)], "src long, dst long")
    start = spark.createDataFrame([(0,)], "mv_id long")
    rows = lambda df: [(r.qid, r["rank"], r.mv_id) for r in df.orderBy("qid", "rank").collect()]
    truth = S.linear_scan(q, o, 5)
    assert rows(R.search_rounds(q, o, ring, 5, 60, start)) == rows(truth)
    narrow = R.search_rounds(q, o, ring, 5, 5, start)
    assert M.recall(narrow, truth, 5).agg(F.avg("recall")).first()[0] <= 1
    links = spark.createDataFrame([(i, 0, j + 1, j, 1.0) for i in range(60) for j in range(60) if i != j], "mv_id long, tok_ix int, pos int, linked_mv long, key double")
    assert rows(R.search_rounds(q, o, ring, 5, 5, start, links, m=60)) == rows(truth)
    few = R.search_rounds(q, o, ring.limit(0), 5, 5, start, links, m=1)
    assert few.groupBy("qid").count().agg(F.max("count")).first()[0] <= 5
    assert R.search_rounds(q.limit(0), o, ring, 5, 5, start).count() == 0
    with pytest.raises(ValueError):
        R.search_rounds(q, o, ring, 5, 4, start)


def test_diverse_choice_and_relinking(spark):
    e = np.eye(4)
    s = G.Shard(IndexConfig(M=2, select="diverse"), np.arange(4), np.concatenate([e[:2], e[:2], e[:2], e[1:3]]), np.full(4, 2))
    assert [n for _, n in s.choose([(0.9, 1), (0.8, 2), (0.6, 3)])] == [1, 3]
    assert [n for _, n in s.choose([(0.9, 1), (0.8, 2)])] == [1, 2]
    o, cfg = S.objects(_small(spark)).persist(), IndexConfig(M=4, ef_construction=16)
    g, gone = G.build_graph(o, cfg).persist(), o.where("mv_id % 3 = 0").select("mv_id")
    plain, mended = G.delete(g, gone), G.delete_relinked(g, o, gone, cfg).persist()
    edges = lambda df: df.agg(F.sum(F.size("nbrs"))).first()[0]
    assert edges(plain) < edges(mended) <= edges(g)
    assert G.check_graph(mended, 4).where("violations > 0").count() == 0
    assert G.delete_relinked(g, o, o.select("mv_id"), cfg).count() == 0


def test_sql_functions(spark):
    FS.register(spark)
    one = "array(array(1D, 0D), array(0D, 1D))"
    r = spark.sql(f"SELECT mv_sim({one}, {one}, 2) AS a, edge_weight({one}, {one}) AS b, vec_dot(array(1D, 2D), array(3D, 4D)) AS c, vec_l2(array(0D, 0D), array(3D, 4D)) AS d, mv_sim(NULL, {one}, 1) AS e").first()
    assert tuple(r) == (1.0, 1.0, 11.0, 5.0, None)
    got = spark.sql(f"SELECT * FROM gamma_nearest(array(0D, 1D), {one}, 5)").collect()
    assert [tuple(x) for x in got] == [(1, 1.0), (0, 0.0)]


def test_datasets_of_orders_and_pages(spark, sf):
    for t in (X.from_orders(spark, sf), X.from_pages(spark, sf)):
        r = t.selectExpr("count(*) n", "count(distinct mv_id, tok_ix) k", "min(size(vec)) lo", "max(size(vec)) hi", "count_if(vec is null) none").first()
        assert r.n == r.k > 0 and (r.lo, r.hi, r.none) == (128, 128, 0)


def test_index_is_saved_grown_thinned_and_checked(spark, tmp_path):
    t = S.normalised(_small(spark)).persist()
    o, q = S.objects(t).persist(), X.as_queries(t, 6)
    cfg = IndexConfig(M=8, ef_construction=32, n_shards=3, shard_by="centroid")
    ix = I.build_index(o.where("mv_id < 50"), cfg, LinkConfig(M=4)).save(f"file://{tmp_path}/a")
    assert all(n > 0 for n in I.size_of(spark, f"file://{tmp_path}/a").values())
    grown = ix.append(o.where("mv_id >= 50")).save(f"file://{tmp_path}/b")
    assert grown.cfg == cfg and grown.objects.count() == 60
    assert grown.validate().where("violations > 0").count() == 0
    rows = lambda df: {(r.qid, r["rank"], r.mv_id) for r in df.collect()}
    truth = S.linear_scan(q, o, 5)
    for mode in ("exact", "clustered"):
        found, stats = grown.search(q, SearchConfig(k=5, ef=60, mode=mode))
        assert rows(found) == rows(truth)
        r = stats.agg(F.sum("lost"), F.min("hops"), F.min("dots"), F.max("scored")).first()
        assert r[0] == 0 and r[1] > 0 and r[2] > 0 and r[3] <= 60
    assert rows(I.search_everywhere(q, grown, SearchConfig(k=5, ef=60))) == rows(truth)
    with pytest.raises(ValueError):
        I.search_everywhere(q, grown, SearchConfig(k=5, ef=60), limit=10)
    thin = grown.delete(o.where("mv_id % 3 = 0").select("mv_id"))
    assert thin.search(q, SearchConfig(k=5, ef=60))[0].where("mv_id % 3 = 0").count() == 0
    assert I.P.n_shards(o, 60 * 4 * 16 * 4 // 4) == 4


def test_clustered_build_and_scores(spark):
    t = S.normalised(_small(spark, 40, 9)).persist()
    o = S.objects(t).persist()
    work = {r: G.build_work(o, IndexConfig(M=6, ef_construction=16, edge_sim=r)).agg(F.sum("dots"), F.sum("scored")).first() for r in ("exact", "clustered")}
    assert all(w[0] > 0 and w[1] > 0 for w in work.values())
    assert G.check_graph(G.build_graph(o, IndexConfig(M=6, ef_construction=16, edge_sim="clustered")), 6).where("violations > 0").count() == 0
    kept = S.cluster_objects(o)
    p = o.select(F.col("mv_id").alias("src")).crossJoin(o.select(F.col("mv_id").alias("dst")))
    a, b = (S.score_pairs(x, x, p, clustered=True) for x in (o, kept))
    assert a.exceptAll(b).count() == 0


def test_cells_decode_and_find(spark):
    t = S.normalised(_small(spark, 80, 5)).persist()
    q, o = X.as_queries(t, 8), S.objects(t)
    cells = B.fit_cells(t, 8, 4)
    x = np.array([r.vec for r in t.collect()])
    assert np.abs(cells.decode(*cells.encode(x)) - x).max() < np.abs(x - cells.centres[cells.nearest(x)]).max()
    codes, truth = B.encode(t, cells).persist(), S.linear_scan(q, o, 5)
    for found in (B.ivf_probe(q, codes, cells, 5, 8, 400), B.residual_centroid(q, codes, cells, 5, 8, 80)):
        assert M.recall(found, truth, 5).agg(F.avg("recall")).first()[0] > 0.7
    for found in (B.token_gather_rerank(q, t, 5, 20), B.pooled_rerank(q, t, 5, 16)):
        assert M.recall(found, truth, 5).agg(F.avg("recall")).first()[0] == 1


def test_windows_cover_whole_texts(spark, tmp_path):
    rows = [(1, " ".join(f"w{i}" for i in range(70))), (2, "one"), (3, None), (4, "a b"), (5, "")]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = X.from_windows(spark, str(tmp_path), 32).collect()
    assert {r.mv_id for r in got} == {1, 4} and sum(r.mv_id == 1 for r in got) == 32 and sum(r.mv_id == 4 for r in got) == 2
    total = sum(X._signs(f"w{i}", 128).astype(int) for i in (0, 1, 2))
    first = next(r.vec for r in got if r.mv_id == 1 and r.tok_ix == 0)
    assert np.floor(total / np.linalg.norm(total) * 127 + 0.5).tolist() == first
