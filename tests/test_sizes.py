"""Queries on small tables that have what larger ones have: parts without an edge, heavy keys, sides that are not sent out."""

import os

import duckdb
import pytest
from pyspark.sql import functions as F

from blendgraph import baselines as B
from blendgraph import oracles
from blendgraph import queries as Q


def parts(spark, folder, keys):
    rows = [(k, f"type {k % 3}") for k in keys]
    spark.createDataFrame(rows, "p_partkey long, p_type string").coalesce(1).write.parquet(f"{folder}/part.parquet")
    return str(folder)


def by_sql(folder, name):
    con = duckdb.connect()
    for table in os.listdir(folder):
        con.execute(f"CREATE VIEW {table.split('.')[0]} AS SELECT * FROM read_parquet('{folder}/{table}/*.parquet')")
    con.execute(f"CREATE TABLE found AS {oracles.oracle_sql()[name]}")
    return con.sql("SELECT * FROM found").limit(10**6).fetchall()


@pytest.mark.parametrize("name", ["link_attachment", "link_jaccard"])
def test_pairs_with_an_isolated_part(spark, tmp_path, name):
    # 1000 and 1121 are a pair beyond the reach, and neither has an edge
    folder = parts(spark, tmp_path, [*range(60), 1000, 1121])
    assert any(r.src == 1000 for r in Q._pairs(spark, folder).collect())
    got = sorted(tuple(r) for r in getattr(Q, name)(spark, folder).select("src", "dst", "is_edge", "score").collect())
    assert got == sorted(by_sql(folder, name)) and got


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_a_salted_join_sends_no_side_out(spark):
    large, small = spark.range(100).select((F.col("id") % 7).alias("k"), "id"), spark.range(7).select(F.col("id").alias("k"), F.lit("x").alias("y"))
    found = Q.O.salted_join(large, small, "k")
    assert "Broadcast" not in plan(found) and found.count() == 100


def test_content_scores_send_no_content_out(spark, tmp_path):
    folder = parts(spark, tmp_path, range(130))
    content, pairs = spark.range(9).select(F.col("id").alias("node"), (F.col("id") % 2).alias("feature"), F.lit(2.0).alias("value")), spark.createDataFrame([(0, 2, 1), (0, 1, 0)], "src long, dst long, is_edge int")
    found = Q.H.content_cosine(content, pairs)
    assert sorted((r.dst, round(r.score, 9)) for r in found.collect()) == [(1, 0.0), (2, 1.0)]
    # the pairs' own join may send scores out: they are as many as the pairs
    assert plan(found).count("BroadcastExchange") <= 1
    assert sorted(tuple(r) for r in Q.link_content(spark, folder).select("src", "dst", "is_edge", "score").collect()) == sorted(by_sql(folder, "link_content"))


def test_planted_source_is_of_the_given_parts(spark, tmp_path):
    # a part that is missing has no edge, and types are the table's
    folder = parts(spark, tmp_path, [k for k in range(200) if k % 7])
    got = sorted(tuple(r) for r in Q.planted_source(spark, folder).collect())
    assert got == sorted(by_sql(folder, "planted_source")) and got
    assert not any(a % 7 == 0 or b % 7 == 0 for a, b, _ in got)


@pytest.mark.parametrize("name", ["loss_init_d4", "grad_nodes_d4", "one_node_step_d4"])
def test_exact_negatives_summed_as_a_function(spark, tmp_path, monkeypatch, name):
    folder = parts(spark, tmp_path, range(200))
    met = []
    monkeypatch.setattr(Q.M, "context_sums", lambda *a, f=Q.M.context_sums: met.append(1) or f(*a, slices=2))
    monkeypatch.setattr(Q.M, "SUMMED_FROM", 1)
    got = sorted(tuple(r) for r in getattr(Q, name)(spark, folder).collect())
    want = sorted(by_sql(folder, name))
    assert met and [r[:-1] for r in got] == [r[:-1] for r in want] and got
    assert max(abs(a[-1] - b[-1]) for a, b in zip(got, want)) < 1.1e-5
    assert sum(a[-1] != b[-1] for a, b in zip(got, want)) < 3


def test_context_label_of_more_nodes_than_a_matrix_of_pairs_holds(spark):
    # a path of 6000 nodes, whose content tells the class
    n = 6000
    e = spark.range(n - 1).select("id", (F.col("id") + 1).alias("o")).select(F.explode(F.expr("array(struct(id AS src, o AS dst), struct(o AS src, id AS dst))")).alias("e")).select("e.*", F.lit(1.0).alias("weight"))
    content = spark.range(n).select(F.col("id").alias("node"), (F.col("id") % 3).alias("feature"), F.lit(2.0).alias("value"))
    train = spark.range(30).select(F.col("id").alias("node"), F.concat(F.lit("c"), F.col("id") % 3).alias("label"))
    vectors, found = B.fit_context_label_mlp(e, content, train, 4, epochs=20)
    assert vectors.count() == n and found.count() == n
    assert found.filter("predicted <> concat('c', node % 3)").isEmpty()


@pytest.fixture(scope="module")
def ring(spark):
    """Counts of a ring, and content of 30 features, 6 a node."""
    n = 300
    cooc = spark.range(n).select(F.col("id").alias("node"), F.explode(F.sequence(F.lit(1), F.lit(9))).alias("k")).select("node", F.expr(f"(node + k) % {n}").alias("context"), F.col("k").alias("cnt"))
    content = spark.range(n).select(F.col("id").alias("node"), F.explode(F.sequence(F.lit(0), F.lit(5))).alias("k")).select("node", F.expr("(node + 5 * k) % 30").alias("feature"), (1.0 + F.col("k")).alias("value"))
    return Q.settle(cooc.unionByName(cooc.select(F.col("context").alias("node"), F.col("node").alias("context"), "cnt")), "ring"), content


#: MB that the ring's contexts took with whole numbers of 8 bytes, less a little.
RING_MB = (24 * 300 + 24 * 1800 + 8 * 300 * 4) / 1e6 - 1e-4


@pytest.mark.parametrize("step", ["fixed", "search", "backtracking", "lipschitz"])
def test_contexts_are_held_in_narrow_numbers(ring, step):
    cooc, content = ring
    cfg = Q.FitConfig(dim=4, max_outer=1, max_inner=1, draws_per_node=4, step=step)
    small, whole = Q.M.fit_joint(cooc, content, cfg, RING_MB), Q.M.fit_joint(cooc, content, cfg)
    # by joins, backtracking is refused and the history would be that of the safe step
    assert Q.M.gather_contexts(cooc, content, 4, RING_MB).feature.itemsize == 1
    losses = [[h[k] for h in r.history for k in ("before", "after")] for r in (small, whole)]
    assert losses[0] == pytest.approx(losses[1]) and small.node_vec.count() == 300


def test_a_pass_deals_no_counts_out(spark, ring):
    cooc, content = ring
    cfg = Q.FitConfig(dim=4, draws_per_node=4)
    model = Q.M.JointModel(cooc, content, cfg, Q.M.gather_contexts(cooc, content, 4))
    vectors, s = Q.M.initial(cooc, model.ctx, cfg)
    keep = lambda p, node, w, h, state: (node, w)
    found = model._blocks(vectors, s, 0, keep, None, "node long, w array<double>", ["node", "w"])
    assert "Exchange" not in plan(found)
    assert sorted(map(tuple, found.collect())) == sorted(map(tuple, vectors.collect()))
    # nor does it where the vectors are joined change what it is
    model.nodes = 10**9
    joined = model._blocks(vectors, s, 0, keep, None, "node long, w array<double>", ["node", "w"])
    assert sorted(map(tuple, joined.collect())) == sorted(map(tuple, vectors.collect()))


def test_pairs_are_dealt_out_once(spark):
    walks = spark.createDataFrame([(0, [1, 2, 1, 3]), (1, [3, 3, 2, 1])], "walk_id long, path array<long>")
    found = Q.C.count_pairs(walks, Q.WalkConfig(walk_length=4, window=2))
    forward = {}
    for path in ([1, 2, 1, 3], [3, 3, 2, 1]):
        for i in range(4):
            for j in range(i + 1, min(i + 3, 4)):
                for key in ((path[i], path[j]), (path[j], path[i])):
                    forward[key] = forward.get(key, 0) + 1
    assert {(r.node, r.context): r.cnt for r in found.collect()} == forward
    assert found._jdf.queryExecution().sparkPlan().toString().count("HashAggregate") <= 2


@pytest.mark.parametrize("extra", [{}, {"homophily": 0.5}, {"margin": 0.5}])
def test_squared_loss_makes_no_two_hop_pairs(spark, tmp_path, monkeypatch, extra):
    folder = parts(spark, tmp_path, [k for k in range(150) if k % 11])
    edges, content = Q.S.planted_graph(spark, folder), Q.S.planted_content(spark, folder)
    labels = Q._types(spark, folder).filter("node % 3 = 0") if "margin" in extra else None
    joined = {r.node: r.w for r in B.fit_squared_content(edges, content, 3, rounds=2, labels=labels, links_mb=0.0, **extra).collect()}

    def refused(*_):
        raise AssertionError("two-hop pairs were made")

    monkeypatch.setattr(B, "two_hop_mean", refused)
    found = {r.node: r.w for r in B.fit_squared_content(edges, content, 3, rounds=2, labels=labels, **extra).collect()}
    assert found.keys() == joined.keys() and len(found) > 100
    assert max(abs(a - b) for k in found for a, b in zip(found[k], joined[k])) < 1e-7


def test_hashed_search_writes_no_candidate_pairs(spark):
    from pyspark.sql import functions as F

    v = spark.range(300).select(F.col("id").alias("node"), F.array(*[F.sin(F.col("id") * (i + 1) * 0.7) for i in range(6)]).alias("w"))
    asked = v.filter("node % 20 = 0").select("node")
    once = Q.E.top_k_hashed(v, 4, asked)
    blocks = Q.E.top_k_hashed(v, 4, asked, query_mb=0.002)
    rows = lambda d: sorted((r.node, r.rank, r.neighbor, round(r.score, 9)) for r in d.collect())
    assert "Join" not in plan(once) and rows(once) == rows(blocks)
    exact = {(r.node, r.neighbor) for r in Q.E.top_k_neighbors(v, 4, asked).collect()}
    assert len(exact & {(r[0], r[2]) for r in rows(once)}) >= 0.9 * len(exact) and len(exact) == 60


def test_rooted_pagerank_writes_no_power(spark, tmp_path):
    folder = parts(spark, tmp_path, [k for k in range(400) if k % 9] + [5000])
    t, roots = Q.G.transition(Q._edges(spark, folder)), Q._queried(spark, folder)
    joined = {(r.src, r.dst): r.value for r in Q.P.rooted_pagerank(t, 0.5, 1e-3, roots, links_mb=0.0).collect()}
    d = Q.P.rooted_pagerank(t, 0.5, 1e-3, roots)
    found = {(r.src, r.dst): r.value for r in d.collect()}
    assert "Join" not in plan(d).split("MapInArrow")[0] and "MapInArrow" in plan(d)
    assert found.keys() == joined.keys() and (5000, 5000) in found
    assert max(abs(found[k] - joined[k]) for k in found) < 1e-12
    assert sorted(tuple(r) for r in Q.rooted_pagerank_roots(spark, folder).collect()) == sorted(by_sql(folder, "rooted_pagerank_roots"))


def test_feature_gradients_come_as_numbers(spark, monkeypatch):
    from pyspark.sql.classic.dataframe import DataFrame

    cooc = spark.createDataFrame([(a, (a * 3 + b) % 7, a + b + 1) for a in range(7) for b in range(3)], "node long, context long, cnt long")
    content = spark.createDataFrame([(a, a, 1.0) for a in range(7)], "node long, feature long, value double")
    cfg = Q.FitConfig(dim=2, draws_per_node=4)
    ctx = Q.M.gather_contexts(cooc, content, 2)
    model = Q.M.JointModel(cooc, content, cfg, ctx)
    node_vec, s = Q.M.initial(cooc, ctx, cfg)

    def refused(*_):
        raise AssertionError("a row for each feature")

    monkeypatch.setattr(DataFrame, "collect", refused)
    g, loss, curve = model.feature_gradient(node_vec, s)
    assert g.shape == (7, 2) and loss > 0 and curve > 0 and abs(g).min() > 0
    d = 1e-5
    change = model.feature_gradient(node_vec, s + d * g)[1] - model.feature_gradient(node_vec, s - d * g)[1]
    assert abs(change / (2 * d) - (g**2).sum()) < 1e-4 * (g**2).sum()


def test_a_regression_has_one_small_task_a_step(spark, monkeypatch):
    from pyspark.ml.classification import OneVsRest

    v = spark.range(200, numPartitions=8).select((F.col("id")).alias("node"), F.array((F.col("id") % 2) * 2.0 - 1, F.sin(F.col("id"))).alias("w"))
    labels = v.select("node", F.when(F.col("node") % 2 == 0, "a").otherwise("b").alias("label"))
    seen, fit = [], OneVsRest.fit
    monkeypatch.setattr(OneVsRest, "fit", lambda self, d, *a: (seen.append(d.rdd.getNumPartitions()), fit(self, d, *a))[1])
    out = Q.E.one_vs_rest(v, Q.E.split_per_class(labels, 20, 100)).collect()
    assert seen == [1] and len(out) == 100 and all(r.label == r.predicted for r in out)


def test_feature_gradients_summed_as_a_function(spark, tmp_path, monkeypatch):
    folder, met = parts(spark, tmp_path, range(200)), []
    monkeypatch.setattr(Q.M, "context_sums", lambda *a, f=Q.M.context_sums: met.append(1) or f(*a, slices=2))
    _, _, _, model, node_vec, s = Q._four(spark, folder)
    pairs = model.feature_gradient(node_vec, s)
    assert not met
    monkeypatch.setattr(Q.M, "SUMMED_FROM", 1)
    sums = model.feature_gradient(node_vec, s)
    assert met and abs(pairs[0] - sums[0]).max() < 1e-8 * abs(pairs[0]).max()
    assert sums[1:] == pytest.approx(pairs[1:], rel=1e-9)
    got, want = sorted(map(tuple, Q.grad_features_d4(spark, folder).collect())), sorted(by_sql(folder, "grad_features_d4"))
    assert [r[:-1] for r in got] == [r[:-1] for r in want] and max(abs(a[-1] - b[-1]) for a, b in zip(got, want)) < 1.1e-5


def test_a_step_alone_makes_no_sums_for_a_loss_after_it(spark, tmp_path, monkeypatch):
    folder, met = parts(spark, tmp_path, range(150)), []
    monkeypatch.setattr(Q.M, "context_sums", lambda *a, f=Q.M.context_sums: met.append(1) or f(*a, slices=2))
    monkeypatch.setattr(Q.M, "SUMMED_FROM", 1)
    assert Q.one_node_step_d4(spark, folder).count() == 4 * 150
    assert len(met) == 1


@pytest.mark.parametrize("few", [True, False])
def test_products_with_links_write_no_column_of_all_entries(spark, monkeypatch, few):
    import tracemalloc

    import numpy as np

    from blendgraph import links as L

    r = np.random.default_rng(7)
    rows, n = np.sort(r.integers(0, 50, 400_000)).astype(np.int32), 50
    at, x = r.integers(0, n, len(rows)).astype(np.int32), r.normal(size=n)
    p, values = (r.integers(0, 9, len(rows)).astype(np.uint8), r.random(9)) if few else (r.random(len(rows)), None)
    monkeypatch.setattr(L, "BLOCK", 1000, raising=False)
    made = L.Links(np.arange(n), np.searchsorted(rows, np.arange(n + 1)), at, p, values)
    full = np.zeros((n, n))
    np.add.at(full, (rows, at), made.entries())
    tracemalloc.start()
    found = made.times(x, rows), made.back(x, rows)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert np.allclose(found[0], full @ x) and np.allclose(found[1], full.T @ x)
    assert most < 8 * len(rows) / 10


def test_links_are_gathered_as_numbers_of_their_values(spark, monkeypatch):
    from blendgraph import links as L

    t = spark.createDataFrame([(10 * a, 10 * ((a * b) % 6), (b + 1) / 7) for a in range(6) for b in range(1, 4) if a], "src long, dst long, p double").groupBy("src", "dst").agg(F.sum("p").alias("p"))
    want = sorted((r.src, r.dst, r.p) for r in t.collect())
    for most in (1 << 16, 1):
        monkeypatch.setattr(L, "MOST_VALUES", most, raising=False)
        got = L.gather_links(t)
        assert sorted(zip(got.ids[got.rows].tolist(), got.ids[got.at].tolist(), got.entries().tolist())) == want
        assert (got.p.itemsize == 1) == (most > 1) and (got.values is None) == (most == 1)


@pytest.mark.parametrize("links", ["between others", "none"])
def test_the_control_of_parts_that_hardly_any_order_holds_together(spark, tmp_path, links):
    labelled = [(k, f"type {k % 2}") for k in range(1200)]
    parts = spark.createDataFrame([(k, t, f"brand {k % 5}", k % 3) for k, t in labelled], "p_partkey long, p_type string, p_brand string, p_size int")
    split = Q.E.split_per_class(spark.createDataFrame(labelled, "node long, label string"), 20, 1000)
    other = [r.node for r in split.filter("part = 'none'").orderBy("node").limit(40).collect()]
    lines = [(2 * (i // 2) + again, k) for again in (0, 1) for i, k in enumerate(other)] if links != "none" else list(enumerate(other))
    parts.coalesce(1).write.parquet(f"{tmp_path}/part.parquet")
    spark.createDataFrame(lines, "l_orderkey long, l_partkey long").coalesce(1).write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.createDataFrame([(k, [float(k % 7), 1.0], k % 2) for k in range(100)], "vec_id long, embedding array<float>, label int").coalesce(1).write.parquet(f"{tmp_path}/embeddings.parquet")
    found = {r.dataset: r for r in Q.negative_control(spark, str(tmp_path)).collect()}
    assert set(found) == {"embeddings", "copurchase"}
    # brands and sizes say nothing of the type: all the others are judged, by chance; where no part has a vector, none is
    low, high = (0.4, 0.6) if links != "none" else (0.0, 0.0)
    assert low <= found["copurchase"].accuracy <= high
