"""Forms for large data held against the joins and windows that they stand for."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from mvspark.config import IndexConfig, SearchConfig
from mvspark.functions import kernel
from mvspark.operators import baselines as B
from mvspark.operators import graph as G
from mvspark.operators import links as L
from mvspark.operators import shards as P
from mvspark.operators import similarity as S
from mvspark.plans import catalogue
from mvspark.sources import fixtures as X


def plan_of(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.fixture(scope="module")
def tok(spark, sf):
    return X.from_embeddings(spark, sf).where("mv_id < 3000000").persist()


@pytest.mark.parametrize("clustered", [False, True])
@pytest.mark.parametrize("kind", ["fused", "raw", "one_sided", "sum"])
def test_every_pair_equals_joined_pairs(tok, kind, clustered):
    o = S.cluster_objects(S.objects(tok))
    p = o.select(F.col("mv_id").alias("src")).crossJoin(o.select(F.col("mv_id").alias("dst")))
    cols = [c for c in o.columns if clustered or c != "groups"]
    want = {(r.src, r.dst): r.weight for r in S.score_pairs(o.select(cols), o.select(cols), p, kind, clustered=clustered).collect()}
    got = {(r.src, r.dst): r.weight for r in S.every_pair(o.select(cols), o.select(cols), kind, clustered=clustered).collect()}
    assert got.keys() == want.keys() and len(got) > 100
    assert all(got[k] == pytest.approx(want[k], abs=1e-6) for k in want)
    u = {r.mv_id: np.array(r.vecs, float) for r in o.collect()}
    if not clustered:
        assert all(v == pytest.approx(kernel.edge_weight(u[a], u[b], edge_fn=kind), abs=1e-6) for (a, b), v in got.items())


def test_every_pair_in_parts(tok, monkeypatch):
    o = S.objects(tok)
    whole = {tuple(r) for r in S.every_pair(o, o, keep=3, skip_own=True).collect()}
    monkeypatch.setattr(S, "QUERY_VALUES", 2000)
    assert {tuple(r) for r in S.every_pair(o, o, keep=3, skip_own=True).collect()} == whole


@pytest.mark.parametrize("name", ["k8_edge_weight", "k8x_raw", "k8x_one_sided", "k8x_sum", "c6_edge_clustered", "k9_symmetry", "k10_cardinality", "k11_consistency"])
def test_pairs_are_not_joined(spark, sf, name):
    plan = plan_of(catalogue.QUERIES[name](spark, sf))
    assert "MapInArrow" in plan and "Join" not in plan


def test_gap_excess_sees_what_breaks_the_bound(tok):
    """With a weight of one for all pairs, every gap is an excess."""
    unit = S.normalised(tok)
    o = S.objects(unit)
    look = S.gap_excess(X.as_queries(unit))
    off = S.every_pair(o, o, other=lambda u, met, w: look(u, met, np.ones(len(w)))).where("src < dst")
    assert off.where("other > 1e-9").count() == off.count() > 0
    assert S.every_pair(o, o, other=look).where("other > 1e-9").count() == 0


def test_bulk_graph_of_many_objects(spark):
    rng = np.random.default_rng(5)
    x = rng.normal(size=(5100, 2, 4)).round(2)
    o = spark.createDataFrame([(i, 2, v.tolist()) for i, v in enumerate(x)], "mv_id long, n_tok int, vecs array<array<double>>").repartition(4)
    g = G.bulk_graph(o, 3)
    near = {}
    for r in g.where("src < 20").collect():
        near.setdefault(r.src, {})[r.dst] = r.weight
    block = kernel.Block(x.reshape(-1, 4), np.full(5100, 2))
    for i in range(20):
        w = block.edges(i, np.arange(5100))
        best = [j for j in np.lexsort((np.arange(5100), -w)) if j != i][:3]
        assert sorted(near[i]) == sorted(best)


def rows(df, *cols) -> list:
    return sorted(tuple(round(x, 6) if isinstance(x, float) else x for x in r) for r in df.select(*cols).collect())


@pytest.mark.parametrize("gamma", [1, 3])
def test_object_wise_forms_equal_set_forms(tok, gamma):
    q, o = X.as_queries(tok), S.objects(tok)
    s = S.token_scores(q, tok).persist()
    groups = q.select("qid", "q_ix", (F.col("q_ix") % 3).alias("g"))
    short = S.shortlists(s, groups, 2)
    links = L.build_links(tok, 4).persist()
    rel = L.relevance(L.contributions(s, gamma), 16129.0)
    pairs = {
        "near": (S.nearest_tokens(q, o, gamma), S.gamma_nn(s, gamma), ("qid", "q_ix", "mv_id", "tok_ix", "s", "rank")),
        "short": (S.shortlisted(q, o, groups, 2), short, ("qid", "g", "mv_id", "tok_ix")),
        "refined": (S.refined_scores(q, o, groups, 2, gamma), S.refined(s, groups, short, gamma), ("qid", "mv_id", "score")),
        "parts": (L.token_parts(q, o, gamma, 16129.0), rel, ("qid", "mv_id", "tok_ix", "part", "rel")),
        "prio": (L.link_priorities(q, o, links, gamma, 16129.0), L.priorities(rel, links), ("qid", "mv_id", "linked_mv", "priority")),
        "top": (L.link_priorities(q, o, links, gamma, 16129.0, m=2), L.top_links(L.priorities(rel, links), 2), ("qid", "mv_id", "linked_mv", "pos")),
    }
    for name, (got, want, cols) in pairs.items():
        got, want = rows(got, *cols), rows(want, *cols)
        assert len(got) == len(want) > 0, name
        assert all(a == pytest.approx(b, abs=2e-6) for a, b in zip(got, want)), name
    assert L.unlike_pops(q, o, links, 4, gamma, 16129.0).count() == 0


def test_unlike_pops_sees_wrong_order(tok):
    """Lists whose keys rise are popped in another order than their priorities have."""
    links = L.build_links(tok, 4)
    wrong = links.withColumn("pos", -F.col("pos"))
    assert L.unlike_pops(X.as_queries(tok), S.objects(tok), wrong, 2, 1, 16129.0).count() > 0


@pytest.mark.parametrize("name", ["k5_gamma_nn", "k6d_general", "c2_filter", "c3_refine", "l5_contribution", "l6_relevance", "l7_priority", "l9_top_links", "l8_equals_l9"])
def test_token_scores_are_not_dealt_out(spark, sf, name):
    """No exchange or window comes after the scores, but for merging k rows a batch or counting."""
    plan = plan_of(catalogue.QUERIES[name](spark, sf))
    above = plan[: plan.index("MapInArrow")]
    assert "MapInPandas" not in above and "Join" not in above
    assert name == "k6d_general" or "Window" not in above


def test_cell_probe_makes_no_rows_of_tokens(spark, sf, tok):
    q = X.as_queries(tok)
    cells = B.fit_cells(tok, 16, 4)
    codes = B.encode(tok, cells)
    got = B.ivf_probe(q, codes, cells, 10, 3, 50, gamma=2)
    plan = plan_of(got)
    assert "Join" not in plan
    ask, missing = B.probes(q, cells, codes, 3, 50)
    looked = set(ask.itertuples(index=False, name=None))
    whole: dict = {}
    for r in codes.collect():
        x = cells.decode(np.array([r.cell]), np.frombuffer(r.code, np.uint8)[None])[0]
        whole.setdefault(r.mv_id, []).append((r.cell, x))
    for qid, m, w in S.query_block(q)[:3]:
        want = []
        for mv, some in whole.items():
            hits = [[float(m[i] @ x) for c, x in some if (qid, i, c) in looked] for i in range(len(m))]
            if any(hits):
                want.append((round(sum(missing[qid][i] + sum(max(s - missing[qid][i], 0) for s in sorted(h)[-2:]) / 2 for i, h in enumerate(hits)), 6), -mv))
        best = sorted(want, reverse=True)[:10]
        assert [(s, -m) for s, m in best] == [(round(r.score, 6), r.mv_id) for r in got.where(F.col("qid") == qid).orderBy("rank").collect()]


def test_centres_are_fitted_on_means(tok, monkeypatch):
    """What comes to the driver is one vector an object, and the centres are those of the same objects' means."""
    o = S.objects(tok).select("mv_id", "n_tok", "vecs")
    some = o.orderBy(F.xxhash64("mv_id"), "mv_id").limit(10).collect()
    x = np.concatenate([P.pooled(np.array(r.vecs, float), np.array([len(r.vecs)])) for r in some])
    came = []
    keep = np.lexsort
    monkeypatch.setattr(P.np, "lexsort", lambda k: came.append(len(k[0])) or keep(k))
    assert np.allclose(P.fit_centres(o, 10, rounds=0, sample=10), x) and came == [10]


def test_wide_list_holds_nodes_without_edges_to_them():
    x = np.random.default_rng(3).normal(size=(40, 2, 8))
    g = G.Shard(IndexConfig(M=4, ef_construction=8), np.arange(40), x.reshape(-1, 8), np.full(40, 2)).insert_all(G.levels(40, IndexConfig(M=4)))
    lost = [i for i in range(30, 40) if i != g.entry]
    for layer in g.near:
        for n, e in layer.items():
            layer[n] = [t for t in e if t[1] not in lost]
    q = np.random.default_rng(4).normal(size=(3, 8))
    found = g.search(q, np.ones(3), SearchConfig(k=40, ef=40, linked=False))
    assert sorted(i for _, i in found) == list(range(40))
    assert len(g.search(q, np.ones(3), SearchConfig(k=5, ef=8, linked=False))) == 5


def test_cosines_are_made_by_blocks(spark, sf, tok):
    assert "NestedLoopJoin" not in plan_of(catalogue.QUERIES["k2_cosine"](spark, sf))
    got = {(r.a, r.i, r.b): r.s for r in S.cosines(tok, S.objects(tok.where("tok_ix = 0"), 1), 6).collect()}
    t = {(r.mv_id, r.tok_ix): np.array(r.vec) for r in tok.collect()}
    assert len(got) == len(t) * sum(1 for _, i in t if not i)
    for (a, i, b), s in list(got.items())[::97]:
        x, y = t[a, i], t[b, 0]
        assert s == pytest.approx(x @ y / np.sqrt(x @ x) / np.sqrt(y @ y), abs=6e-7)


def test_asked_pairs_carry_no_vectors(tok):
    """A pair is two ids until its source's task scores it, so rounds and cells don't deal out vectors with every pair."""
    o = S.objects(tok)
    p = o.select(F.col("mv_id").alias("src")).crossJoin(o.select(F.col("mv_id").alias("dst")))
    plan = plan_of(S.score_pairs(o, o, p))
    assert "collect_list(dst" in plan and plan.count("vecs") > 0 and "v#" not in plan


@pytest.mark.parametrize("more", [False, True])
def test_cells_meet_without_rows_of_pairs(spark, tok, more, monkeypatch):
    """Objects of a cell are scored by tasks that hold them; only the best leave. ``more``: some objects in two cells, and two parts."""
    o = S.objects(tok).persist()
    c = o.select("mv_id", F.pmod(F.xxhash64("mv_id"), F.lit(3)).alias("cell"))
    if more:
        c = c.unionByName(o.where("mv_id % 3 = 0").select("mv_id", F.lit(1).cast("long").alias("cell")))
        monkeypatch.setattr(S, "QUERY_VALUES", -(-S.values_of(o) // 2))
    df = G.bulk_graph(o, 3, c)
    plan = plan_of(df)
    assert "collect_list(dst" not in plan and "cell" in plan
    one = c.distinct()
    pairs = one.select(F.col("mv_id").alias("src"), "cell").join(one.select(F.col("mv_id").alias("dst"), "cell"), "cell").where("src <> dst").select("src", "dst").distinct()
    truth: dict = {}
    for r in S.every_pair(o, o, skip_own=True).join(pairs, ["src", "dst"]).collect():
        truth.setdefault(r.src, []).append((-r.weight, r.dst))
    got: dict = {}
    for r in df.collect():
        got.setdefault(r.src, []).append((-r.weight, r.dst))
    assert {k: sorted(v) for k, v in got.items()} == {k: sorted(v)[:3] for k, v in truth.items()} and truth


def test_queries_of_a_graph_are_dealt_over_tasks(spark, tok, monkeypatch):
    """Runs of queries walk side by side; answers and counters are those of one run."""
    o, cfg = G.with_shards(S.objects(tok), 1), IndexConfig(M=8, ef_construction=16)
    g, links, q = G.build_graph(o, cfg).persist(), L.shard_links(o, L.LinkConfig(M=4)).persist(), X.as_queries(tok)
    out = []
    for n in (1 << 30, 2):
        monkeypatch.setattr(G, "QUERIES", n)
        found, stats = G.search_graph(q, o, g, SearchConfig(k=5, ef=16, scale=16129.0), cfg, links)
        out.append([sorted(map(tuple, d.collect())) for d in (found, stats.drop("ms"))])
        assert len(out[0][0])
    assert out[0] == out[1]
    assert "run#" in plan_of(found).split("FlatMapCoGroups")[1][:400]


def test_shards_of_any_size_get_their_links(spark, tok, monkeypatch):
    """A shard of more tokens than a bound is not refused, and its links are those of the scan."""
    monkeypatch.setattr(L, "TOKENS", 10, raising=False)
    o = S.objects(tok)
    got = {tuple(r) for r in L.shard_links(o.withColumn("shard", F.lit(3)), L.LinkConfig(M=4, gamma=2)).collect()}
    want = {(3, *r) for r in L.build_links(S.to_tokens(o), 4, 2).select("mv_id", "tok_ix", "pos", "linked_mv", "key").collect()}
    assert got == want and len(got) > 100


@pytest.mark.parametrize("block, width", [(1, 1), (3, 7), (64, 50), (512, 1 << 20)])
def test_nearest_tokens_by_parts(block, width):
    """Whatever part of the tokens is met at a time, the nearest and their order (ties by place) are those of all at once."""
    r = np.random.default_rng(4)
    owner = np.repeat(np.arange(40), r.integers(1, 9, 40))
    x = r.integers(-2, 3, (len(owner), 3)).astype(np.float32)
    s = np.where(owner[:, None] == owner, -np.inf, x @ x.T)
    for n in (1, 6, 500):
        parts = list(L.nearest_exact(x, owner, n, block, width))
        row, col, val = (np.concatenate(c) for c in zip(*parts))
        for i in range(len(x)):
            want = [j for j in np.lexsort((np.arange(len(x)), -s[i])) if owner[j] != owner[i]][:n]
            assert col[row == i].tolist() == want and val[row == i].tolist() == s[i][want].tolist()


def test_full_list_is_as_wide_as_the_data(spark, monkeypatch):
    """A walk over 5100 objects answers as the scan does, even where the best are on nodes that no edge and no link leads to."""
    n, led = 5100, 5020
    t = spark.range(n).selectExpr("id AS mv_id", "explode(array(0, 1)) AS tok_ix", "array(cast(id as double), 1D) AS vec")
    ring = f"array((id + 1) % {led}, (id + {led} - 1) % {led})"
    g = spark.range(n).selectExpr(
        "0 AS shard", "0 AS layer", "id AS mv_id", "0 AS top_layer", f"CASE WHEN id < {led} THEN {ring} ELSE array() END AS nbrs",
        f"CASE WHEN id < {led} THEN array(1D, 1D) ELSE array() END AS weights", "id = 0 AS entry",
    )
    none = spark.createDataFrame([], "shard int, mv_id long, tok_ix int, pos int, linked_mv long, key double")
    monkeypatch.setattr(catalogue, "tok", lambda *_: t)
    monkeypatch.setattr(catalogue.G, "build_graph", lambda *_: g)
    monkeypatch.setattr(catalogue.L, "shard_links", lambda *_: none)
    monkeypatch.setattr(catalogue.X, "as_queries", lambda t: t.where("mv_id = 7").select(F.col("mv_id").alias("qid"), F.col("tok_ix").alias("q_ix"), "vec"))
    got = [tuple(r) for r in catalogue.l10_search_full_ef(spark, "").orderBy("rank").collect()]
    assert got == [(7, k + 1, n - 1 - k, 14.0 * (n - 1 - k) + 2) for k in range(10)]


@pytest.mark.parametrize("name", ["k6_example1", "k6_example2", "k12_counterexample", "r_recursive"])
def test_worked_jobs_read_a_table(spark, sf, name):
    import __spark_entry__ as entry

    plan = plan_of(entry.queries()[name](spark, sf))
    assert "parquet" in plan and "LocalTableScan" not in plan


def test_every_batch_teaches_once_counts_are_settled():
    """Between two settlings batches teach, too: only those before the first have nothing to predict by."""
    from mvspark.llm import lm_score

    pace, taught, due = lm_score.Pace(), [], []
    for _ in range(60):
        taught.append(pace.bits > 0)
        due.append(pace.due(lm_score.SOONEST // 2))
    first = due.index(True)
    assert not any(taught[: first + 1]) and all(taught[first + 1 :]) and due.count(False) > 10
    assert pace.bits + pace.pending == 60 * (lm_score.SOONEST // 2)
