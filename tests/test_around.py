"""Streams, SQL functions, operators, sources and baselines."""

import datetime as dt
import time

import pytest
from pyspark.sql import functions as F

from blendgraph import baselines as B
from blendgraph import cooccur as C
from blendgraph import graph as G
from blendgraph import operators as O
from blendgraph import sources as S
from blendgraph import workloads as W
from blendgraph.config import FitConfig, WalkConfig
from blendgraph.functions import arrow_cosine, arrow_vec_sum, register_functions
from blendgraph.streaming import CountSink, session_walks, stream_pairs, window_counts

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def events(spark):
    t = dt.datetime(2024, 1, 1)
    rows = [(i, t + dt.timedelta(minutes=m), u, n) for i, (u, m, n) in enumerate([(1, 0, 5), (1, 10, 6), (1, 20, 5), (1, 90, 7), (2, 0, 8), (2, 5, 9), (1, 95, 5)])]
    return spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long, node long").withColumn("event_type", F.lit("x")).withColumn("value", F.lit(1.0))


def test_sessions_and_windows(events):
    got = sorted((r.user_id, list(r.path)) for r in session_walks(events).collect())
    assert got == [(1, [5, 6, 5]), (1, [7, 5]), (2, [8, 9])]
    assert sorted((r.n, r.total) for r in window_counts(events, "1 hour").collect()) == [(2, 2.0), (5, 5.0)]
    assert sum(r.n for r in window_counts(events, "1 hour", "30 minutes").collect()) == 14


def test_stream_equals_batch_and_replay_adds_nothing(spark, events, tmp_path):
    cfg = WalkConfig(walk_length=3, per_node=1, window=2)
    src = str(tmp_path / "in")
    events.filter("user_id = 1").coalesce(1).write.parquet(src)
    events.filter("user_id = 2").coalesce(1).write.mode("append").parquet(src)
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(src)
    sink = CountSink(str(tmp_path / "counts"), cfg)
    walks = session_walks(stream, "30 minutes", watermark="0 seconds")
    q = walks.writeStream.outputMode("append").foreachBatch(sink).option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    got = {(r.node, r.context): r.cnt for r in sink.read(spark).collect()}
    want = {(r.node, r.context): r.cnt for r in C.count_pairs(session_walks(events.filter("ts < '2024-01-01 01:00:00'")), cfg).collect()}
    assert got and all(want.get(k) == v for k, v in got.items())
    sink(session_walks(events), 7)
    once = sink.read(spark).agg(F.sum("cnt")).first()[0]
    sink(session_walks(events), 7)
    assert sink.read(spark).agg(F.sum("cnt")).first()[0] == once


def test_window_tail_keeps_state_across_batches(spark, events, tmp_path):
    src = str(tmp_path / "in")
    for i in range(3):
        events.filter(f"event_id % 3 = {i} AND user_id = 1").coalesce(1).write.mode("append").parquet(src)
    stream = spark.readStream.schema(events.schema).parquet(src)
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    q = stream_pairs(stream, 2).writeStream.outputMode("append").format("memory").queryName("tail_pairs").option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    n = events.filter("user_id = 1").count()
    assert spark.table("tail_pairs").count() == 1 + 2 * (n - 2)


def test_sql_functions(spark):
    assert "cosine_sim" in register_functions(spark)
    r = spark.sql("SELECT sigmoid(0D) s, round(softplus(0D), 6) p, cosine_sim(array(1D, 0D), array(1D, 0D)) c, cosine_sim(array(0D), array(1D)) z, hash_u('7|3|2') h, arrow_cosine(array(3D, 4D), array(4D, 3D)) a").first()
    assert (r.s, r.p, r.c, r.z) == (0.5, 0.693147, 1.0, 0.0) and r.h == 1441584268 / 2**32 and abs(r.a - 0.96) < 1e-12
    pairs = spark.sql("SELECT * FROM pairs_in_window(array(1L, 2L, 3L), 2)").collect()
    assert sorted(map(tuple, pairs)) == [(1, 2, 1), (1, 3, 2), (2, 3, 1)]
    walk = spark.sql("SELECT * FROM walk_from(1L, map(1L, array(2L), 2L, array(1L)), 4, 1)").collect()
    assert [x.node for x in walk] == [1, 2, 1, 2]
    d = spark.createDataFrame([([1.0, 2.0],), ([3.0, 4.0],)], "v array<double>")
    assert d.agg(arrow_vec_sum("v").alias("s")).first().s == [4.0, 6.0] and d.select(arrow_cosine("v", "v").alias("c")).first().c == pytest.approx(1)


def test_operators(spark):
    d = spark.range(30).withColumnRenamed("id", "k")
    assert O.band_join(d, d, "k", -2, 3).count() == sum(1 for a in range(30) for b in range(30) if a - 2 <= b <= a + 3)
    hot = spark.createDataFrame([(1, i) for i in range(50)] + [(2, 0)], "k int, x int")
    assert O.salted_join(hot, spark.createDataFrame([(1, "a"), (3, "b")], "k int, y string"), "k").count() == 50
    with pytest.raises(ValueError):
        O.exact_pairs(d.withColumnRenamed("k", "node"), 10)
    joined = O.co_bucketed_join(d, d.withColumn("y", F.col("k") * 2), "k", "bucketed_test", 4)
    assert joined.count() == 30


def test_readers_and_writers(spark, tmp_path):
    e = spark.createDataFrame([(1, 2, 1.5), (2, 1, 1.5)], "src long, dst long, weight double")
    for fmt in ("parquet", "orc", "csv", "json"):
        e.write.format(fmt).save(str(tmp_path / fmt))
        assert S.read_edges(spark, str(tmp_path / fmt), fmt).orderBy("src").collect() == e.collect()
    v = spark.createDataFrame([(1, [0.5, 1.0])], "node long, w array<double>")
    S.write_vectors(v, str(tmp_path / "v"), 2)
    S.write_word2vec_text(v, str(tmp_path / "t"))
    assert spark.read.parquet(str(tmp_path / "v")).collect() == v.collect() and spark.read.text(str(tmp_path / "t")).first()[0] == "1 0.5 1.0"
    S.write_cooc(e.selectExpr("src AS node", "dst AS context", "1L AS cnt"), str(tmp_path / "c"), 4)
    assert spark.read.parquet(str(tmp_path / "c")).count() == 2
    S.write_model_card(spark, str(tmp_path / "m"), {"dim": 2})
    assert spark.read.text(str(tmp_path / "m")).first()[0] == '{"dim": 2}'


def test_two_cliques_are_told_apart(spark):
    """Every embedding puts nodes of one clique nearer to each other than to the other clique."""
    pairs = [(a, b) for base in (0, 10) for a in range(base, base + 8) for b in range(a + 1, base + 8)] + [(0, 10)]
    e = G.mirrored(spark.createDataFrame([(a, b, 1.0) for a, b in pairs], "src long, dst long, weight double"))
    content = G.nodes_of(e).select("node", (F.col("node") / 10).cast("int").alias("feature"), F.lit(1.0).alias("value"))
    labels = G.nodes_of(e).select("node", F.when(F.col("node") < 10, "a").otherwise("b").alias("label"))
    d = W.Data(e, content, labels, "cliques")
    train = labels.filter("node % 10 < 2")
    fit = FitConfig(dim=4, max_outer=6)
    from blendgraph import evaluate as E
    from blendgraph import factorize as M

    walks = WalkConfig(walk_length=10, per_node=5, window=2)
    vectors = {
        "joint": M.fit_joint(W.counts_of(e, walks), content, fit).node_vec,
        "squared": B.fit_squared_content(e, content, 2, rounds=4),
        "homophily": B.fit_squared_content(e, content, 2, rounds=4, homophily=0.5),
        "margin": B.fit_squared_content(e, content, 2, rounds=4, labels=train, margin=0.5),
        "spectral": B.fit_spectral_fusion(e, content, train, 2),
    }
    for name, v in vectors.items():
        r = E.class_separation(v, labels, 3).first()
        assert r.within > r.across + 0.2, name
    for name, p in (("conv", B.fit_graph_conv(e, content, train)), ("mlp", B.fit_context_label_mlp(e, content, train, 4)[1])):
        assert p.join(labels, "node").filter("label <> predicted").count() == 0, name
    with pytest.raises(ValueError):
        B.fit_spectral_fusion(e, content, train, 2, max_nodes=5)
    assert d.name == "cliques"


def test_planted_counts_of_the_smallest_tables(spark):
    assert S.planted_graph(spark, SF).count() == 2 * 656 and S.copurchase_graph(spark, SF).count() == 2 * 8899
    assert S.same_host_graph(spark, SF).count() == 2 * 34 and S.shingle_graph(spark, SF).count() == 2 * 386


def test_planted_source_as_table_and_stream(spark, tmp_path):
    from blendgraph.sources import PlantedEdges

    spark.dataSource.register(PlantedEdges)
    load = lambda read: read.format("planted_edges").option("nodes", 60).option("rowsPerBatch", 25).load()
    want = {(a, b) for a in range(60) for b in range(a + 1, a + 121) if (7919 * a + 104729 * b) % 1009 < (200 if a % 6 == b % 6 else 8)}
    table = load(spark.read)
    assert {(r.src, r.dst) for r in table.collect()} == want and table.rdd.getNumPartitions() == 4
    q = load(spark.readStream).writeStream.format("memory").queryName("planted").option("checkpointLocation", str(tmp_path / "c")).start()
    try:
        for _ in range(60):
            if spark.table("planted").count() == len(want):
                break
            time.sleep(0.5)
        assert {(r.src, r.dst) for r in spark.table("planted").collect()} == want
    finally:
        q.stop()


def test_graphs_keep_frequent_items(spark):
    from blendgraph.sources.graphs import shared_item_graph

    items = spark.createDataFrame([(i, "host") for i in range(30)] + [(i, "small") for i in (3, 7, 9)], "node long, item string")
    got = {(r.src, r.dst): r.weight for r in shared_item_graph(items, 2, 10).collect()}
    assert got == {**{(0, i): 1.0 for i in range(1, 30)}, **{(i, 0): 1.0 for i in range(1, 30)}, **{(a, b): 1.0 for a in (3, 7, 9) for b in (3, 7, 9) if a != b}}
    assert len(shared_item_graph(items, 2, 10, beyond="none").collect()) == 6


def test_copies_of_any_number_are_connected(spark, tmp_path):
    from blendgraph.sources import shingle_graph

    text = " ".join(f"w{i}" for i in range(12))
    rows = [(i, text if i < 20 else text + f" tail{i} end{i}" if i < 23 else f"alone {i} x y z") for i in range(25)] + [(99, None)]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    got = {(r.src, r.dst): r.weight for r in shingle_graph(spark, str(tmp_path)).collect()}
    assert all(got[0, i] == 10.0 for i in range(1, 20)) and got[0, 20] == got[20, 21] == 10.0
    assert not any(23 in k or 24 in k or 99 in k for k in got)


def test_folds_and_hashed_neighbors(spark):
    import numpy as np

    from blendgraph import evaluate as E

    labels = spark.createDataFrame([(i, "a" if i < 13 else "b") for i in range(20)], "node long, label string")
    sizes = {}
    for r in E.folds(labels, 5).collect():
        sizes[r.label, r.fold] = sizes.get((r.label, r.fold), 0) + 1
    assert [sizes["a", k] for k in range(1, 6)] == [3, 3, 3, 2, 2] and [sizes["b", k] for k in range(1, 6)] == [2, 2, 1, 1, 1]
    r = np.random.default_rng(0)
    v = spark.createDataFrame([(i, [float(x) for x in r.normal(size=8)]) for i in range(200)], "node long, w array<double>")
    asked = v.filter("node % 20 = 0").select("node")
    exact = {(x.node, x.neighbor) for x in E.top_k_neighbors(v, 3, asked).collect()}
    found = {(x.node, x.neighbor) for x in E.top_k_hashed(v, 3, asked).collect()}
    assert len(exact & found) >= 0.9 * len(exact) == 27


def test_graph_convolution_by_joins_is_the_same(spark):
    import numpy as np

    r = np.random.default_rng(1)
    pairs = sorted({tuple(sorted(map(int, r.choice(16, 2, replace=False)))) for _ in range(30)})
    e = G.mirrored(spark.createDataFrame([(a, b, 1.0) for a, b in pairs], "src long, dst long, weight double"))
    content = spark.createDataFrame([(i, int(f), 1.0) for i in range(18) for f in r.choice(7, 2, replace=False)], "node long, feature int, value double")
    train = spark.createDataFrame([(i, "ab"[i % 2]) for i in range(8)], "node long, label string")
    a = {x.node: x.predicted for x in B.fit_graph_conv(e, content, train, hidden=4, epochs=6, rate=0.1).collect()}
    b = {x.node: x.predicted for x in B.fit_graph_conv_joins(e, content, train, hidden=4, epochs=6, rate=0.1).collect()}
    assert a == b and len(b) == 18 and len(set(b.values())) == 2
