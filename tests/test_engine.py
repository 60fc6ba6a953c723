"""Exact fixtures of the engine on small graphs."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from blendgraph import cooccur as C
from blendgraph import evaluate as E
from blendgraph import factorize as M
from blendgraph import graph as G
from blendgraph import heuristics as H
from blendgraph import proximity as P
from blendgraph.config import FitConfig, WalkConfig
from blendgraph.plans import GraphStats, choose, estimate
from blendgraph.randomness import numpy_draw
from blendgraph.ranks import ranked, ranked_within
from blendgraph.walks import sample_walks, sample_walks_biased


def edges(spark, pairs, weight=1.0):
    return G.mirrored(spark.createDataFrame([(a, b, weight) for a, b in pairs], "src long, dst long, weight double")).coalesce(1)


@pytest.fixture(scope="module")
def path(spark):
    return edges(spark, [(0, 1), (1, 2), (2, 3)]).cache()


def dense(df, n, value="value"):
    out = np.zeros((n, n))
    for r in df.collect():
        out[r.src, r.dst] = r[value]
    return out


def test_mean_proximity_of_a_path(path):
    t = G.transition(path)
    want = np.array([[1 / 6, 7 / 12, 1 / 6, 1 / 12], [7 / 24, 1 / 4, 3 / 8, 1 / 12]])
    got = dense(P.expected_cooc(t, 3), 4)
    assert np.allclose(got[:2], want) and np.allclose(got[2:], want[::-1, ::-1])
    p = dense(t, 4, "p")
    assert np.allclose(dense(P.two_hop_mean(t), 4), (p + p @ p) / 2)


def test_rooted_pagerank_against_inverse(spark, path):
    t = G.transition(path)
    nodes = spark.range(5).withColumnRenamed("id", "node")
    got = dense(P.rooted_pagerank(t, 0.5, 1e-7, nodes=nodes), 5)
    assert np.allclose(got[:4, :4], P.dense_rooted_pagerank(dense(t, 4, "p"), 0.5), atol=1e-6)
    assert np.allclose(got[:4].sum(axis=1), 1, atol=1e-6) and got[4, 4] == 0.5


@pytest.mark.parametrize(("ring", "beta", "k", "gap", "bound", "pre"), [(3, 0.5, 4, 0.4083, 1.9375, 1.7375), (5, 0.85, 11, 0.1923, 1.7155, 1.1681)])
def test_gap_on_regular_graphs(spark, ring, beta, k, gap, bound, pre):
    r = P.proximity_gap_dense(G.transition(edges(spark, [(i, (i + 1) % ring) for i in range(ring)])), 40, beta)
    assert r["k_split"] == k and r["premise_symmetric"] and r["applicable"] and r["gap"] <= r["bound"]
    assert np.allclose([r["gap"], r["bound"], r["pre_bound"]], [gap, bound, pre], atol=1e-4)


def test_gap_premises(spark, path):
    r = P.proximity_gap_dense(G.transition(path), 40, 0.5)
    assert not r["premise_symmetric"] and abs(r["sigma_max"] - 1.1441) < 1e-4
    assert not P.gap_bounds(5, 0.85)["applicable"] and P.gap_bounds(5, 0.85)["k_split"] == -2
    with pytest.raises(ValueError):
        P.proximity_gap_dense(G.transition(path), 40, 0.5, max_nodes=3)


def test_gap_without_powers(path):
    """By products with vectors, against the matrices: the series ends at a tail of 0.01."""
    t = G.transition(path)
    got, want = P.proximity_gap(t, 3, 0.3, 1e-2, 12, 1e-4).first(), P.proximity_gap_dense(t, 3, 0.3)
    assert abs(got.gap - want["gap"]) < 0.02 and abs(got.sigma_max - want["sigma_max"]) < 0.01
    assert (got.k_split, got.bound, got.premise_symmetric) == (want["k_split"], want["bound"], want["premise_symmetric"])


def test_heuristics(spark, path):
    pair = spark.createDataFrame([(0, 2), (0, 3)], "src long, dst long")
    score = lambda f: {r.dst: r.score for r in f(path, pair).collect()}
    assert score(H.common_neighbors) == {2: 1, 3: 0} and score(H.jaccard) == {2: 0.5, 3: 0}
    assert abs(score(H.adamic_adar)[2] - 1 / math.log(2)) < 1e-9 and score(H.preferential_attachment) == {2: 2, 3: 1}


def test_ranking_measures(spark):
    s = lambda rows: spark.createDataFrame([(i, i, e, float(x)) for i, (e, x) in enumerate(rows)], "src long, dst long, is_edge int, score double")
    assert E.auc(s([(1, 1), (0, 1), (1, 1), (0, 1)])).first()[0] == 0.5
    assert E.auc(s([(1, 3), (1, 2), (0, 1)])).first()[0] == 1 and E.auc(s([(0, 3), (1, 2)])).first()[0] == 0
    assert abs(E.mean_average_precision(s([(1, 3), (0, 2), (1, 1)])).first()[0] - 0.833333) < 1e-6


def test_draws_and_walk_modes_agree(spark, path):
    from blendgraph.randomness import fast_draw

    rows = spark.range(50).select("id", fast_draw(7, F.col("id"), F.lit(3).cast("long")).alias("d")).collect()
    assert [r.d for r in rows] == numpy_draw(7, np.arange(50), 3).tolist()
    cfg = WalkConfig(walk_length=9, per_node=3, window=3)
    a, b = (sample_walks(path, cfg, mode=m) for m in ("broadcast", "hops"))
    assert sorted(map(tuple, ((r.walk_id, *r.path) for r in a.collect()))) == sorted(map(tuple, ((r.walk_id, *r.path) for r in b.collect())))
    many, few = (sorted(map(tuple, C.count_pairs(sample_walks(path.repartition(n), cfg), cfg).collect())) for n in (7, 1))
    assert many == few


def test_count_identities(spark, path):
    cfg = WalkConfig(walk_length=40, per_node=1, window=5)
    w = sample_walks(path, cfg)
    c = C.count_pairs(w, cfg)
    assert c.agg(F.sum("cnt")).first()[0] == 4 * 370
    m = {(r.node, r.context): r.cnt for r in c.collect()}
    assert all(m[b, a] == n for (a, b), n in m.items())
    assert all(abs(a - b) == 1 for r in w.collect() for a, b in zip(r.path, r.path[1:]))
    biased = sample_walks_biased(path, WalkConfig(walk_length=6, per_node=2), p=1e6, q=1.0).collect()
    inner = [r.path for r in biased]
    assert all(abs(a - b) == 1 for p in inner for a, b in zip(p, p[1:]))


def test_label_pairs(spark):
    labels = spark.createDataFrame([(i, "a" if i < 5 else "b") for i in range(9)] + [(99, "alone")], "node long, label string")
    two = labels.filter("label <> 'alone'")
    assert C.label_pairs(two, 300).agg(F.sum("cnt")).first()[0] == 600
    c = C.label_pairs(labels, 300, symmetric=False)
    assert c.filter("node = 99 OR node = context").isEmpty()
    lab = {r.node: r.label for r in labels.collect()}
    assert all(lab[r.node] == lab[r.context] for r in c.collect())
    got, want = ({(r.node, r.context): r[2] for r in d.collect()} for d in (C.label_pairs(two, 40_000, symmetric=False), C.expected_label_pairs(two, 40_000)))
    assert all(abs(got[k] - v) < 6 * math.sqrt(v) for k, v in want.items())
    assert C.label_pairs(two, 0).isEmpty()
    nodes = spark.createDataFrame([(0,), (42,)], "node long")
    assert [r.node for r in C.isolated_nodes(nodes, got and C.label_pairs(two, 300)).collect()] == [42]


@pytest.fixture(scope="module")
def small_model(spark):
    r = np.random.default_rng(0)
    pairs = sorted({tuple(sorted(map(int, r.choice(14, 2, replace=False)))) for _ in range(40)})
    cooc = edges(spark, pairs).select(F.col("src").alias("node"), F.col("dst").alias("context"), (1 + (F.col("src") + F.col("dst")) % 4).alias("cnt")).cache()
    content = spark.createDataFrame([(i, int(f), float(v)) for i in range(14) for f, v in zip(r.choice(6, 3, replace=False), r.random(3))], "node long, feature int, value double").cache()
    cfg = FitConfig(dim=3, max_outer=6, max_inner=2, seed=5, negative_mode="exact", step="lipschitz")
    ctx = M.gather_contexts(cooc, content)
    return cooc, content, cfg, ctx


def full_loss(ctx, node_ids, cooc, w, s, k=1.0):
    n = np.zeros((len(node_ids), len(ctx.ids)))
    for r in cooc.collect():
        n[np.searchsorted(node_ids, r.node), np.searchsorted(ctx.ids, r.context)] = r.cnt
    q = k * np.outer(n.sum(axis=1), n.sum(axis=0)) / n.sum()
    x = w @ ctx.dictionary(s).T
    return ((n + q) * np.logaddexp(0, x) - n * x).sum()


def test_gradients_against_differences(spark, small_model):
    cooc, content, cfg, ctx = small_model
    model = M.JointModel(cooc, content, cfg, ctx)
    node_vec, s = M.initial(cooc, ctx, cfg)
    rows = node_vec.orderBy("node").collect()
    ids, w = np.array([r.node for r in rows]), np.array([r.w for r in rows])
    g = {r.node: np.array(r.g) for r in model.node_gradients(node_vec, s).collect()}
    gs, loss, _ = model.feature_gradient(node_vec, s)
    base = full_loss(ctx, ids, cooc, w, s)
    assert abs(base - loss) < 1e-8
    for i in range(3):
        d = np.zeros_like(w)
        d[i, i] = 1e-6
        assert abs((full_loss(ctx, ids, cooc, w + d, s) - full_loss(ctx, ids, cooc, w - d, s)) / 2e-6 - g[ids[i]][i]) < 1e-4
        d = np.zeros_like(s)
        d[i, i] = 1e-6
        assert abs((full_loss(ctx, ids, cooc, w, s + d) - full_loss(ctx, ids, cooc, w, s - d)) / 2e-6 - gs[i, i]) < 1e-4


def test_loss_never_rises(small_model):
    cooc, content, cfg, _ = small_model
    for step in ("lipschitz", "search", "backtracking"):
        h = M.fit_joint(cooc, content, cfg.with_(step=step)).history
        losses = [x for r in h for x in (r["before"], r["after"])]
        assert all(b <= a + 1e-9 * abs(a) for a, b in zip(losses, losses[1:])) and losses[-1] < losses[0]


def test_optimum_is_shifted_pmi(small_model):
    cooc = small_model[0]
    both = M.pair_cap(cooc, 2.0).join(M.shifted_pmi(cooc, 2.0), ["node", "context"])
    off = both.select(F.max(F.abs(M.expected_count(F.col("cap"), F.col("spmi")) - F.col("cnt")))).first()[0]
    assert off < 1e-9


def test_sampled_negatives_are_unbiased(spark, small_model):
    cooc, content, cfg, ctx = small_model
    exact = M.JointModel(cooc, content, cfg, ctx)
    node_vec, s = M.initial(cooc, ctx, cfg)
    want = exact.feature_gradient(node_vec, s)[1]
    model = M.JointModel(cooc, content, cfg.with_(negative_mode="sampled", draws_per_node=200), ctx)
    got = np.array([model.feature_gradient(node_vec, s, turn)[1] for turn in range(8)])
    assert abs(got.mean() - want) < 4 * got.std() / math.sqrt(8) + 0.02 * abs(want)


def test_losses_against_plain(small_model):
    cooc, content, cfg, ctx = small_model
    r = np.random.default_rng(4)
    rows = cooc.collect()
    nodes = np.array(sorted({x.node for x in rows}))
    n = np.zeros((len(nodes), len(ctx.ids)))
    for x in rows:
        n[np.searchsorted(nodes, x.node), np.searchsorted(ctx.ids, x.context)] = x.cnt
    total = n.sum(axis=1)
    w, h = r.normal(size=(len(nodes), 3)), r.normal(size=(len(ctx.ids), 3))
    x = w @ h.T
    want = {
        "sgns": ((n + 2 * np.outer(total, n.sum(axis=0)) / n.sum()) * np.logaddexp(0, x) - n * x).sum(axis=1),
        "logistic_uncapped": ((n + 2) * np.logaddexp(0, x) - n * x).sum(axis=1),
        "squared": 0.5 * ((x - n / total[:, None]) ** 2).sum(axis=1),
    }
    at, cnt = [np.flatnonzero(v) for v in n], [v[v > 0] for v in n]
    for loss, each in want.items():
        exact = M.Pairs(ctx, at, cnt, total, cfg.with_(loss=loss, negatives=2.0), nodes, 0)
        assert np.allclose(exact.losses(exact.scores(w, h)), each)
        drawn = [M.Pairs(ctx, at, cnt, total, cfg.with_(loss=loss, negatives=2.0, negative_mode="sampled", draws_per_node=4000), nodes, t) for t in range(3)]
        mean = np.mean([p.losses(p.scores(w, h)) for p in drawn], axis=0)
        assert np.allclose(mean, each, rtol=0.1, atol=0.05 * np.abs(each).max())
        g = exact.to_nodes(exact.residual(x), h)
        for i in range(3):
            d = np.zeros_like(w)
            d[i, i] = 1e-6
            a, b = (exact.losses(exact.scores(v, h)).sum() for v in (w + d, w - d))
            assert abs((a - b) / 2e-6 - g[i, i]) < 1e-4


def vectors(fit):
    return {r.node: r.w for r in fit.node_vec.collect()}, {r.feature: r.s for r in fit.feat_vec.collect()}


@pytest.mark.parametrize("loss", ["sgns", "logistic_uncapped", "squared"])
def test_joins_make_the_same_fit(small_model, loss):
    """The path by joins and the one by broadcast have the same draws, steps and losses."""
    cooc, content, cfg, _ = small_model
    cfg = cfg.with_(negative_mode="sampled", draws_per_node=5, max_outer=1, max_inner=1, loss=loss)
    a, b = M.fit_joint(cooc, content, cfg), M.fit_joint(cooc, content, cfg, broadcast_mb=0)
    for x, y in zip(vectors(a), vectors(b)):
        assert x.keys() == y.keys() and all(np.allclose(x[k], y[k], atol=1e-9) for k in x)
    for x, y in zip(a.history, b.history):
        assert x["half"] == y["half"] and np.allclose([x["before"], x["after"]], [y["before"], y["after"]]) and x["after"] <= x["before"]
    with pytest.raises(ValueError):
        M.fit_by_joins(cooc, content, cfg.with_(negative_mode="exact"))


def test_draws_do_not_depend_on_the_plan(spark, small_model):
    cooc, content, cfg, _ = small_model
    cfg = cfg.with_(negative_mode="sampled", draws_per_node=6, max_outer=1)
    one = vectors(M.fit_joint(cooc, content, cfg))[0]
    before = spark.conf.get("spark.sql.shuffle.partitions")
    try:
        spark.conf.set("spark.sql.shuffle.partitions", "3")
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "2")
        other = vectors(M.fit_joint(cooc.repartition(5), content, cfg))[0]
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert all(np.allclose(one[k], other[k], atol=1e-9) for k in one)


def test_biased_walks_follow_their_law(spark):
    """On a triangle with a tail 0-1-2-0, 2-3: shares of the steps 1 -> 2 -> x against the weights 1/p, 1 and 1/q."""
    g = edges(spark, [(0, 1), (1, 2), (2, 0), (2, 3)])
    p, q = 0.25, 0.5
    steps = [r.path for r in sample_walks_biased(g, WalkConfig(walk_length=3, per_node=1500), p, q).collect()]
    ends = [x[2] for x in steps if x[:2] == [1, 2]]
    want = {1: 1 / p, 0: 1.0, 3: 1 / q}
    for node, weight in want.items():
        assert abs(ends.count(node) / len(ends) - weight / sum(want.values())) < 0.05
    assert len(ends) > 500 and all(x[2] == 2 for x in steps if x[1] == 3)


def test_ranks(spark):
    r = np.random.default_rng(2)
    rows = [(int(i), "abc"[i % 3] if i % 10 else None, int(r.integers(0, 9)), int(r.integers(0, 5))) for i in range(300)]
    d = spark.createDataFrame(rows, "id long, g string, k int, v int").repartition(7)
    got = {x.id: (x.rank, x.s) for x in ranked(d, [F.desc("k"), "id"], {"s": "v"}).collect()}
    total = 0
    for i, x in enumerate(sorted(rows, key=lambda x: (-x[2], x[0])), 1):
        total += x[3]
        assert got[x[0]] == (i, total)
    got = {x.id: (x.rank, x.s) for x in ranked_within(d, "g", [F.desc("k"), "id"], {"s": "v"}).collect()}
    for g in (None, "a", "b", "c"):
        total = 0
        for i, x in enumerate(sorted((x for x in rows if x[1] == g), key=lambda x: (-x[2], x[0])), 1):
            total += x[3]
            assert got[x[0]] == (i, total)
    assert ranked(d.limit(0), ["id"]).collect() == [] and ranked_within(d.limit(0), "g", ["id"]).collect() == []


def test_hubs_are_cut_into_chunks(spark):
    from blendgraph.walks import adjacency

    star = edges(spark, [(0, i) for i in range(1, 41)])
    heads, chunks = adjacency(star, chunk=8)
    assert max(len(x.nbrs) for x in chunks.collect()) < 30 and heads.filter("node = 0").first().total == 40
    assert sorted(n for x in chunks.filter("node = 0").collect() for n in x.nbrs) == list(range(1, 41))


def test_untrained_nodes_and_content_only(spark, small_model):
    cooc, content, cfg, _ = small_model
    r = M.fit_joint(cooc, content.unionByName(spark.createDataFrame([(77, 1, 2.0)], "node long, feature int, value double")), cfg.with_(max_outer=2))
    nodes = spark.createDataFrame([(0,), (77,)], "node long")
    assert {x.node: x.trained for x in r.trained(nodes).collect()} == {0: True, 77: False}
    full = r.complete(nodes, content.unionByName(spark.createDataFrame([(77, 1, 2.0)], "node long, feature int, value double")))
    assert full.filter("node = 77").count() == 1


def test_split_keeps_components(spark):
    ring = edges(spark, [(i, (i + 1) % 12) for i in range(12)] + [(0, 6), (3, 9), (20, 21)])
    r = E.split_invariants(ring, 0.9).first()
    assert r.components_before == r.components_after == 2 and r.hidden == 15 - 12 and r.hidden_not_edge == r.non_edge_is_edge == 0
    assert G.spanning_forest(ring).count() == 12 and not G.is_connected(ring)


def test_validation(spark):
    bad = spark.createDataFrame([(1, 2, 1.0), (1, 2, 1.0), (3, 3, 0.0), (None, 1, 1.0)], "src long, dst long, weight double")
    r = G.validate(bad).first()
    assert (r.edges, r.null_ids, r.bad_weights, r.self_loops, r.duplicated_pairs) == (4, 1, 1, 1, 1) and r.one_way_pairs >= 1
    clean = G.symmetrize(bad.filter("src IS NOT NULL"), "one")
    assert sorted((x.src, x.dst, x.weight) for x in clean.collect()) == [(1, 2, 1.0), (2, 1, 1.0)]


def test_plans(spark, path):
    stats = GraphStats.of(path)
    assert (stats.nodes, stats.edges, stats.max_degree) == (4, 6, 2) and choose(stats)["walks"] == "broadcast"
    huge = GraphStats(10**9, 10**11, 1e15, 10**7)
    assert choose(huge) == choose(huge) | {"walks": "hops", "negatives": "sampled", "context_side": "joins", "adjacency": "chunks"}
    assert estimate(stats)["pairs_per_walk"] == 370
