"""The experiments, on the graphs of the given tables. Every function returns a DataFrame with one row a method."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import baselines as B
from . import evaluate as E
from . import factorize as M
from . import graph as G
from . import heuristics as H
from . import sources as S
from .checkpoints import settle
from .config import FitConfig, WalkConfig
from .content import content_onehot, content_tfidf
from .cooccur import count_pairs, label_pairs, merge_counts
from .proximity import two_hop_mean
from .walks import sample_walks

QUICK = FitConfig(dim=16, max_outer=10, max_inner=2)
WALKS = WalkConfig()


class Data:
    """A graph with content and labels, each written once."""

    def __init__(self, edges: DataFrame, content: DataFrame, labels: DataFrame, name: str):
        self.edges, self.content, self.labels, self.name = settle(edges, "edges"), settle(content, "content"), settle(labels, "labels"), name
        self.spark = edges.sparkSession


def planted_data(spark: SparkSession, sf_dir: str) -> Data:
    """Planted parts with planted weak content."""
    e, c = S.planted_graph(spark, sf_dir), S.planted_content(spark, sf_dir)
    labels = S.read_table(spark, sf_dir, "part").select(F.col("p_partkey").alias("node"), F.col("p_type").alias("label"))
    return Data(e, c, labels, "planted parts")


def document_data(spark: SparkSession, sf_dir: str, label: str = "lang", size: int = 300) -> Data:
    docs = S.read_table(spark, sf_dir, "documents")
    if label == "lang":
        labels = docs.select(F.col("doc_id").alias("node"), F.col("lang").alias("label"))
    else:
        labels = S.read_table(spark, sf_dir, "labels").select(F.col("doc_id").alias("node"), F.col(label).cast("string").alias("label"))
    return Data(S.shingle_graph(spark, sf_dir), content_tfidf(docs, size), labels, "documents")


def counts_of(edges: DataFrame, cfg: WalkConfig = WALKS) -> DataFrame:
    return settle(count_pairs(sample_walks(edges, cfg), cfg), "cooc")


def _all_nodes(d: Data) -> DataFrame:
    return d.content.select("node").unionByName(G.nodes_of(d.edges)).distinct()


def _rows(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


# --- classification ---------------------------------------------------------------------------------------------------


def _accuracy(vectors: DataFrame, split: DataFrame) -> float:
    """0 where no test node has a vector, or no train node: then none gets its class."""
    return float(E.accuracy(E.one_vs_rest(vectors, split)).first().accuracy or 0.0)


def classify_unsupervised(d: Data, per_class: int = 20, test: int = 1000, fit: FitConfig = QUICK, walks: WalkConfig = WALKS, seed: int = 7, methods: tuple[str, ...] = ("joint", "counts_only", "skipgram", "squared_content", "squared_homophily", "content_only", "majority")) -> DataFrame:
    """Accuracy of one-vs-rest logistic regression on vectors that have seen no label."""
    split = settle(E.split_per_class(d.labels, per_class, test, seed), "split")
    cooc = counts_of(d.edges, walks)
    runs: dict[str, Callable[[], float]] = {
        "joint": lambda: _accuracy(_completed(M.fit_joint(cooc, d.content, fit), d), split),
        "counts_only": lambda: _accuracy(M.fit_counts_only(cooc, fit).node_vec, split),
        "skipgram": lambda: _accuracy(B.uniform_walk_skipgram(d.edges, fit.dim, walks), split),
        "biased_skipgram": lambda: _accuracy(B.biased_walk_skipgram(d.edges, fit.dim, walks), split),
        "squared_content": lambda: _accuracy(B.fit_squared_content(d.edges, d.content, fit.dim), split),
        "squared_homophily": lambda: _accuracy(B.fit_squared_content(d.edges, d.content, fit.dim, homophily=0.5), split),
        "content_only": lambda: _accuracy(B.content_vectors(d.content, d.content.agg(F.max("feature")).first()[0] + 1), split),
        "majority": lambda: float(E.accuracy(E.majority_class(split)).first().accuracy),
    }
    return _rows(d.spark, [(d.name, m, runs[m]()) for m in methods], "dataset string, method string, accuracy double")


def _completed(r: M.FitResult, d: Data) -> DataFrame:
    return settle(r.complete(_all_nodes(d), d.content), "completed")


def classify_semi_supervised(d: Data, per_class: int = 20, test: int = 1000, label_ratio: float = 0.01, fit: FitConfig = QUICK, walks: WalkConfig = WALKS, seed: int = 7, methods: tuple[str, ...] = ("joint_labels", "squared_margin", "spectral_fusion", "context_label", "graph_conv"), max_nodes: int = 5000) -> DataFrame:
    """As above, for methods that see the train labels, and those alone. label_ratio: label rounds over structure counts."""
    split = settle(E.split_per_class(d.labels, per_class, test, seed), "split")
    train = split.filter("part = 'train'").select("node", "label")

    def joint() -> float:
        cooc = counts_of(d.edges, walks)
        rounds = round(label_ratio * (cooc.agg(F.sum("cnt")).first()[0] or 0))
        return _accuracy(_completed(M.fit_joint(merge_counts(cooc, label_pairs(train, rounds, seed)), d.content, fit), d), split)

    def predicted(p: DataFrame) -> float:
        return float(E.accuracy(split.filter("part = 'test'").join(p, "node", "left").fillna("", ["predicted"])).first().accuracy)

    runs = {
        "joint_labels": joint,
        "squared_margin": lambda: _accuracy(B.fit_squared_content(d.edges, d.content, fit.dim, labels=train, margin=0.5), split),
        "spectral_fusion": lambda: _accuracy(B.fit_spectral_fusion(d.edges, d.content, train, fit.dim, max_nodes), split),
        "context_label": lambda: predicted(B.fit_context_label_mlp(d.edges, d.content, train, fit.dim)[1]),
        "graph_conv": lambda: predicted(B.fit_graph_conv(d.edges, d.content, train, max_nodes=max_nodes)),
    }
    return _rows(d.spark, [(d.name, m, runs[m]()) for m in methods], "dataset string, method string, accuracy double")


def sensitivity_grid(d: Data, ks: tuple[float, ...] = (1.0, 5.0), ratios: tuple[float, ...] = (0.0, 0.01, 0.1), seeds: tuple[int, ...] = (1, 2), per_class: int = 20, test: int = 500, fit: FitConfig = QUICK.with_(max_outer=5), walks: WalkConfig = WALKS) -> DataFrame:
    """Mean accuracy over the seeds for each number of negatives k and each share of label rounds m (0: no labels)."""
    rows = []
    for seed in seeds:
        split = settle(E.split_per_class(d.labels, per_class, test, seed), "split")
        train = split.filter("part = 'train'").select("node", "label")
        cooc = counts_of(d.edges, replace(walks, seed=seed))
        total = cooc.agg(F.sum("cnt")).first()[0] or 0
        for ratio in ratios:
            both = cooc if not ratio else settle(merge_counts(cooc, label_pairs(train, round(ratio * total), seed)), "merged")
            for k in ks:
                r = M.fit_joint(both, d.content, fit.with_(negatives=k, seed=seed))
                rows.append((k, ratio, seed, _accuracy(_completed(r, d), split)))
    all_rows = _rows(d.spark, rows, "k double, label_ratio double, seed int, accuracy double")
    return all_rows.groupBy("k", "label_ratio").agg(F.avg("accuracy").alias("accuracy"), F.coalesce(F.stddev("accuracy"), F.lit(0.0)).alias("spread"), F.count("*").alias("runs"))


def embedding_picture(d: Data, fit: FitConfig = QUICK, walks: WalkConfig = WALKS) -> DataFrame:
    """What a picture of the embedding would show, as numbers: separation of the classes by method."""
    vectors = {"joint": M.fit_joint(counts_of(d.edges, walks), d.content, fit).node_vec, "biased_skipgram": B.biased_walk_skipgram(d.edges, fit.dim, replace(walks, walk_length=min(walks.walk_length, 6))), "squared_content": B.fit_squared_content(d.edges, d.content, fit.dim)}
    out = None
    for name, v in vectors.items():
        row = E.class_separation(settle(v, "vectors"), d.labels).select(F.lit(name).alias("method"), "within", "across", "knn_agreement")
        out = row if out is None else out.unionByName(row)
    return out


# --- link prediction --------------------------------------------------------------------------------------------------


def predict_links(d: Data, fraction: float = 0.5, fit: FitConfig = QUICK, walks: WalkConfig = WALKS, seed: int = 7, methods: tuple[str, ...] = ("joint", "counts_only", "skipgram", "squared_content", "squared_homophily", "common_neighbors", "jaccard", "adamic_adar", "attachment", "content_only", "chance")) -> DataFrame:
    """Hide edges, embed what is left, score hidden edges against as many non-edges: AUC and MAP."""
    residual, pairs, share = E.link_split(d.edges, fraction, seed)
    cooc = counts_of(residual, walks)
    cosine = lambda v: E.cosine_pairs(v, pairs)
    runs = {
        "joint": lambda: cosine(M.fit_joint(cooc, d.content, fit).complete(_all_nodes(d), d.content)),
        "counts_only": lambda: cosine(M.fit_counts_only(cooc, fit).node_vec),
        "skipgram": lambda: cosine(B.uniform_walk_skipgram(residual, fit.dim, walks)),
        "biased_skipgram": lambda: cosine(B.biased_walk_skipgram(residual, fit.dim, walks)),
        "squared_content": lambda: cosine(B.fit_squared_content(residual, d.content, fit.dim)),
        "squared_homophily": lambda: cosine(B.fit_squared_content(residual, d.content, fit.dim, homophily=0.5)),
        "common_neighbors": lambda: H.common_neighbors(residual, pairs),
        "jaccard": lambda: H.jaccard(residual, pairs),
        "adamic_adar": lambda: H.adamic_adar(residual, pairs),
        "attachment": lambda: H.preferential_attachment(residual, pairs),
        "content_only": lambda: H.content_cosine(d.content, pairs),
        "chance": lambda: H.hash_score(pairs),
    }
    rows = []
    for m in methods:
        s = settle(runs[m](), "scores")
        rows.append((d.name, m, float(E.auc(s).first()[0]), float(E.mean_average_precision(s).first()[0]), float(share)))
    return _rows(d.spark, rows, "dataset string, method string, auc double, map double, hidden_share double")


def case_study(d: Data, fit: FitConfig = QUICK, walks: WalkConfig = WALKS) -> DataFrame:
    """Two pairs of one class, one linked and one not, by hash order: their cosine in two embeddings."""
    lab = d.labels.select("node", "label")
    one = d.edges.filter("src < dst").join(lab.withColumnRenamed("node", "src"), "src").join(lab.select(F.col("node").alias("dst"), F.col("label").alias("l2")), "dst").filter("label = l2")
    linked = one.orderBy(F.xxhash64("src", "dst")).limit(1).select("src", "dst", F.lit(True).alias("linked"))
    # neighbours in hash order within a class, without the edges among them
    ends = E.ranked_within(d.edges.select(F.col("src").alias("node")).distinct().join(lab, "node").withColumn("h", F.xxhash64("node")), "label", ["h", "node"], rank="r")
    ends = settle(ends, "ends")
    other = ends.select("label", "r", F.col("node").alias("src")).join(ends.select("label", (F.col("r") - 1).alias("r"), F.col("node").alias("dst")), ["label", "r"])
    other = other.join(d.edges.select("src", "dst"), ["src", "dst"], "left_anti").orderBy(F.xxhash64("src", "dst")).limit(1).select("src", "dst", F.lit(False).alias("linked"))
    pairs = settle(linked.unionByName(other), "cases")
    a = E.cosine_pairs(M.fit_joint(counts_of(d.edges, walks), d.content, fit).node_vec, pairs).withColumnRenamed("score", "joint")
    b = E.cosine_pairs(B.fit_squared_content(d.edges, d.content, fit.dim), pairs).withColumnRenamed("score", "squared_content")
    return a.join(b, ["src", "dst", "linked"])


def window_ablation(d: Data, windows: tuple[int, ...] = (2, 5), fit: FitConfig = QUICK, walks: WalkConfig = WALKS) -> DataFrame:
    """Link AUC with counts of a short and a long window."""
    residual, pairs, _ = E.link_split(d.edges)
    rows = []
    for w in windows:
        cooc = counts_of(residual, replace(walks, window=w))
        s = settle(E.cosine_pairs(M.fit_joint(cooc, d.content, fit).node_vec, pairs), "scores")
        rows.append((w, float(cooc.count()), float(E.auc(s).first()[0])))
    return _rows(d.spark, rows, "window int, pairs double, auc double")


def sparsity_effect(spark: SparkSession, sf_dir: str, fit: FitConfig = QUICK, walks: WalkConfig = WALKS) -> DataFrame:
    """Joint against counts only on sparser and denser graphs of the same documents."""
    docs = S.read_table(spark, sf_dir, "documents")
    content, labels = content_tfidf(docs), docs.select(F.col("doc_id").alias("node"), F.col("lang").alias("label"))
    out = None
    for name, e in (("shared lines", S.line_graph(spark, sf_dir)), ("two shingles", S.shingle_graph(spark, sf_dir)), ("one shingle", S.shingle_graph(spark, sf_dir, 1))):
        d = Data(e, content, labels, name)
        r = predict_links(d, fit=fit, walks=walks, methods=("joint", "counts_only"))
        r = r.withColumn("edges", F.lit(d.edges.count() // 2))
        out = r if out is None else out.unionByName(r)
    return out


def transfer(spark: SparkSession, sf_dir: str, dims: tuple[int, ...] = (8, 16), fit: FitConfig = QUICK.with_(max_outer=6), walks: WalkConfig = WALKS) -> DataFrame:
    """The dimension that is best on the documents' graph, used on the planted and the copurchase graph."""
    docs = document_data(spark, sf_dir)
    tuned = max(dims, key=lambda k: predict_links(docs, fit=fit.with_(dim=k), walks=walks, methods=("joint",)).first().auc)
    out = None
    for d in (planted_data(spark, sf_dir), copurchase_data(spark, sf_dir)):
        r = predict_links(d, fit=fit.with_(dim=tuned), walks=walks, methods=("joint",)).withColumn("tuned_dim", F.lit(tuned))
        out = r if out is None else out.unionByName(r)
    return out


def copurchase_data(spark: SparkSession, sf_dir: str, least_shared: int = 2) -> Data:
    """Random by construction: the negative control."""
    part = S.read_table(spark, sf_dir, "part")
    labels = part.select(F.col("p_partkey").alias("node"), F.col("p_type").alias("label"))
    return Data(S.copurchase_graph(spark, sf_dir, least_shared), content_onehot(part, "p_partkey", ["p_brand", "p_size"]), labels, "copurchase")


def negative_control(spark: SparkSession, sf_dir: str, fit: FitConfig = QUICK, walks: WalkConfig = WALKS) -> DataFrame:
    """Labels that nothing explains must stay at chance: the vectors of the embeddings table and their label, and parts by
    chance bought together. Few parts are, so the others of the split are judged by their content's vectors."""
    v = S.read_table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("node"), F.col("embedding").cast("array<double>").alias("w"), F.col("label").cast("string").alias("label"))
    split = settle(E.split_per_class(v.select("node", "label"), 20, 1000), "split")
    rows = [("embeddings", _accuracy(v.select("node", "w"), split), float(E.accuracy(E.majority_class(split)).first().accuracy))]
    d = copurchase_data(spark, sf_dir)
    split = settle(E.split_per_class(d.labels, 20, 1000), "split")
    r = M.fit_joint(counts_of(d.edges, walks), d.content, fit)
    rows.append(("copurchase", _accuracy(r.complete(split.filter("part <> 'none'"), d.content), split), float(E.accuracy(E.majority_class(split)).first().accuracy)))
    return _rows(spark, rows, "dataset string, accuracy double, majority double")


def user_recommendation(spark: SparkSession, sf_dir: str, fit: FitConfig = QUICK.with_(max_outer=5), walks: WalkConfig = WALKS) -> DataFrame:
    """Users' relations with their features: the users' graph with event types as content."""
    e = S.read_table(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count("*").cast("double").alias("value"))
    types = e.select("event_type").distinct()
    numbered = types.select("event_type", (F.expr("row_number() OVER (ORDER BY event_type)") - 1).alias("feature"))
    users = e.join(F.broadcast(numbered), "event_type").select(F.col("user_id").alias("node"), F.col("feature").cast("long").alias("feature"), "value")
    edges = S.user_key_graph(spark, sf_dir)
    # keys have no events of their own: each is its own feature, behind the event types
    keys = G.nodes_of(edges).join(users.select("node").distinct(), "node", "left_anti").select("node", F.col("node").alias("feature"), F.lit(1.0).alias("value"))
    from .content import normalized

    d = Data(edges, normalized(users).unionByName(keys), users.select("node", F.lit("user").alias("label")).distinct(), "users and keys")
    return predict_links(d, 0.2, fit, walks, methods=("joint", "common_neighbors", "attachment", "chance"))


def isolated_rescue(spark: SparkSession, sf_dir: str, ratio: float = 0.02, fit: FitConfig = QUICK, walks: WalkConfig = WALKS, seed: int = 7) -> DataFrame:
    """Every fifth part is cut off, half of those are labelled: how often the nearest connected nodes have a cut-off node's
    class, without and with label context."""
    d = planted_data(spark, sf_dir)
    cut = d.labels.filter("node % 5 = 0").select("node", "label", ((F.col("node") / 5).cast("long") % 2 == 0).alias("labelled"))
    edges = settle(d.edges.filter("src % 5 <> 0 AND dst % 5 <> 0"), "cut")
    known = cut.filter("labelled").select("node", "label").unionByName(E.split_per_class(d.labels.filter("node % 5 <> 0"), 20, 0, seed).filter("part = 'train'").select("node", "label"))
    cooc = counts_of(edges, walks)
    total = cooc.agg(F.sum("cnt")).first()[0] or 0
    rows = []
    for share in (0.0, ratio):
        counts = merge_counts(cooc, label_pairs(known, round(share * total), seed)) if share else cooc
        r = M.fit_joint(counts, d.content, fit)
        moved = r.trained(_all_nodes(d))
        v = r.node_vec.unionByName(M.init_vectors(moved.filter("NOT trained").select("node"), "node", "node", fit.dim, fit.dim**-0.5, fit.seed))
        linked = settle(v.join(G.nodes_of(edges), "node", "left_semi"), "linked")
        for labelled in (True, False):
            asked = v.join(cut.filter(F.col("labelled") == labelled).select("node"), "node", "left_semi")
            both = settle(linked.unionByName(asked), "asked")
            near = E.top_k_neighbors(both, 5, asked.select("node")).join(G.nodes_of(edges).withColumnRenamed("node", "neighbor"), "neighbor", "left_semi")
            hit = near.join(d.labels, "node").join(d.labels.select(F.col("node").alias("neighbor"), F.col("label").alias("other")), "neighbor").agg(F.avg((F.col("label") == F.col("other")).cast("double"))).first()[0]
            rows.append((share, labelled, float(hit or 0.0)))
    return _rows(spark, rows, "label_ratio double, labelled boolean, agreement double")


def scale_stages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds and rows of each stage on the copurchase and the bipartite graph."""
    rows = []

    def timed(name: str, f: Callable[[], DataFrame]) -> DataFrame:
        t = time.time()
        out = settle(f(), name.replace(" ", "-"))
        n = out.count()
        rows.append((name, n, time.time() - t))
        return out

    few = WalkConfig(walk_length=10, per_node=2)
    for name, graph in (("copurchase", lambda: S.copurchase_graph(spark, sf_dir)), ("bipartite", lambda: S.bipartite_graph(spark, sf_dir))):
        e = timed(f"{name} graph", graph)
        timed(f"{name} transition", lambda: G.transition(e))
        w = timed(f"{name} walks", lambda: sample_walks(e, few))
        c = timed(f"{name} counts", lambda: count_pairs(w, few))
        timed(f"{name} caps", lambda: M.pair_cap(c))
    timed("copurchase two_hop_mean", lambda: two_hop_mean(G.transition(S.copurchase_graph(spark, sf_dir, 2))))
    return _rows(spark, rows, "stage string, n long, seconds double")
