"""Other embeddings to compare with. Each returns vectors(node, w) or predictions.

Skip-gram on walks is the engine's Word2Vec. The squared-loss family is solved exactly, half by half. The last three
methods are only named where they are compared, so their formulas follow public descriptions of their kind; they work on
the driver, up to max_nodes, and are approximate by that token. The context-label network keeps lists there, no matrix of
all pairs.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .checkpoints import settle
from .config import WalkConfig
from .factorize import Contexts, gather_contexts, init_vectors, lists_of, summed, vec_sum
from .graph import degrees, transition
from .links import LINKS_MB, Links, gather_links
from .pair_sums import _sliced
from .proximity import two_hop_mean
from .walks import sample_walks, sample_walks_biased


def fit_walk_skipgram(walks: DataFrame, dim: int = 16, window: int = 5, seed: int = 7, max_iter: int = 1, parts: int | None = None, step: float = 0.025) -> DataFrame:
    """Skip-gram vectors of the nodes in walks. parts tasks train side by side and are averaged after each pass; one for
    each 50,000 walks unless told otherwise."""
    from pyspark.ml.feature import Word2Vec
    from pyspark.ml.functions import vector_to_array

    sentences = walks.select(F.expr("transform(path, x -> CAST(x AS STRING))").alias("s"))
    if parts is None:
        parts = max(1, walks.count() // 50_000)
    model = Word2Vec(vectorSize=dim, windowSize=window, minCount=0, inputCol="s", outputCol="v", seed=seed, maxIter=max_iter, numPartitions=parts, stepSize=step).fit(sentences)
    return model.getVectors().select(F.col("word").cast("long").alias("node"), vector_to_array("vector").alias("w"))


def uniform_walk_skipgram(edges: DataFrame, dim: int = 16, cfg: WalkConfig = WalkConfig()) -> DataFrame:
    return fit_walk_skipgram(settle(sample_walks(edges, cfg), "walks"), dim, cfg.window, cfg.seed)


def biased_walk_skipgram(edges: DataFrame, dim: int = 16, cfg: WalkConfig = WalkConfig(), p: float = 1.0, q: float = 0.5) -> DataFrame:
    return fit_walk_skipgram(settle(sample_walks_biased(edges, cfg, p, q), "walks"), dim, cfg.window, cfg.seed)


# --- squared loss ------------------------------------------------------------------------------------------------------


def fit_squared_content(edges: DataFrame, content: DataFrame, dim: int = 16, reg: float = 0.2, rounds: int = 8, homophily: float = 0.0, labels: DataFrame | None = None, margin: float = 0.0, seed: int = 7, links_mb: float = LINKS_MB) -> DataFrame:
    """The two-hop mean as (content · feature embedding) · node vector, by squared loss; w holds both factors' parts.

    Each half has a closed form. homophily pulls linked nodes' vectors together: a node's neighbours enter its equations as
    they were the round before. margin adds a linear classifier of the labelled nodes, of which only they see the error.
    Features × features numbers are solved for on the driver, so content has some thousand features at most.
    """
    links = gather_links(transition(edges), links_mb)
    if links is None:
        return _fit_squared_by_joins(edges, content, dim, reg, rounds, homophily, labels, margin, seed)
    spark = edges.sparkSession
    ctx = gather_contexts(edges.select(F.col("src").alias("node"), F.col("dst").alias("context"), F.col("weight").alias("cnt")), content, dim)
    if ctx is None or len(ctx.features) > 8000:
        raise ValueError("the content side is too large for the closed form")
    classes = [r.label for r in labels.select("label").distinct().orderBy("label").collect()] if labels is not None and margin else []
    nodes = init_vectors(edges.select(F.col("src").alias("node")).distinct(), "node", "node", dim, dim**-0.5, seed)
    number = F.coalesce(F.array_position(F.lit(classes), F.col("label")) - 1, F.lit(-1)).cast("int") if classes else F.lit(-1)
    nodes = settle((nodes.join(labels.select("node", "label"), "node", "left") if classes else nodes).select("node", "w", number.alias("label")), "nodes")
    gram = _gram_of_contexts(spark, ctx) if len(ctx.features) <= 1000 else _content_gram(content, ctx)
    sent, ids = spark.sparkContext.broadcast((links, ctx)), links.ids
    del links
    f, k = len(ctx.features), len(classes)
    base, back = gram + reg * np.eye(len(gram)), None
    s = prev = now = None
    u = np.zeros((dim, len(classes)))
    for turn in range(rounds + 1):
        if back is not None:
            back.destroy()
        back = spark.sparkContext.broadcast((s, prev, u, None if s is None else s.T @ gram @ s))
        made = nodes.mapInArrow(_squared_pass(sent, back, uuid.uuid4().hex, dim, reg, homophily, margin, len(classes), bool(homophily)), _PASSED)
        made = settle(made, "round") if homophily else made
        sums = sum((np.frombuffer(r.sums).reshape(-1, dim) for r in made.filter("sums IS NOT NULL").select("sums").collect()), np.zeros((f + 2 * dim + max(1, k), dim)))
        if homophily:
            now = _matrix_of(made.filter("sums IS NULL"), ids, dim)
        y, ww, own, each = np.split(sums, [f, f + dim, f + 2 * dim])
        u_next = np.linalg.solve(own + reg * np.eye(dim), each[:k].T) if k and turn else u
        s_next = np.linalg.solve(ww + reg * np.eye(dim), np.linalg.solve(base, y).T).T
        if turn == rounds:
            break
        s, prev, u = s_next, now, u_next
    # the last vectors are made once more, beside the context dictionary of the features that follow from them
    final = spark.sparkContext.broadcast((s, prev, u, s.T @ gram @ s, s_next))
    return nodes.mapInArrow(_squared_pass(sent, final, uuid.uuid4().hex, dim, reg, homophily, margin, len(classes), True), _PASSED).filter("sums IS NULL").select("node", "w")


_PASSED = "node long, w array<double>, sums binary"
#: What this worker process made last for a pass: tasks of a pass share it.
_HELD: dict[str, tuple] = {}


def _whole(links: Links, ctx: Contexts, h: np.ndarray) -> np.ndarray:
    """One number a context as one of every node."""
    if len(ctx.ids) == len(links.ids):
        return h
    out = np.zeros(len(links.ids))
    out[np.searchsorted(links.ids, ctx.ids)] = h
    return out


def _right_sides(links: Links, ctx: Contexts, given: tuple, homophily: float, key: str) -> tuple:
    """The nodes' right sides, a column at a time, and the dictionary of the features after, where it is asked for."""
    if key not in _HELD:
        _HELD.clear()
        s, prev, _, _, *after = given
        b, h = None, None
        if s is not None:
            b, rows = np.empty((len(links.ids), s.shape[1]), order="F"), links.rows
            for c in range(s.shape[1]):
                x = _whole(links, ctx, ctx.dictionary(s[:, c : c + 1])[:, 0])
                b[:, c] = links.times((x + links.times(x, rows)) / 2, rows)
                if homophily:
                    b[:, c] += homophily * links.times(np.ascontiguousarray(prev[:, c]), rows)
        if after:
            h = np.empty((len(links.ids), s.shape[1]), order="F")
            for c in range(s.shape[1]):
                h[:, c] = _whole(links, ctx, ctx.dictionary(after[0][:, c : c + 1])[:, 0])
        _HELD[key] = b, h
    return _HELD[key]


def _squared_pass(sent, given, key: str, dim: int, reg: float, homophily: float, margin: float, classes: int, listed: bool):
    """One pass over nodes(node, w, label): their vectors by the features given (the first ones as they are, before there are
    features). Each task gives one row of sums: transposed content times its part of the two-hop mean's transpose times the
    vectors, the vectors' products, those of the labelled ones, and each class's sum. listed: the vectors too; beside the
    features after, joined with the context's, both of length 1."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        links, ctx = sent.value
        s, _, u, product, *after = given.value
        whole, ww, own, each, seen = None, np.zeros((dim, dim)), np.zeros((dim, dim)), np.zeros((max(1, classes), dim)), False
        for batch in batches:
            if not batch.num_rows:
                continue
            seen = True
            b, h = _right_sides(links, ctx, given.value, homophily, key)
            node, label = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 2))
            at = np.searchsorted(links.ids, node)
            if s is None:
                w = batch.column(1).flatten().to_numpy(zero_copy_only=False).reshape(-1, dim)
            else:
                left = product + (reg + homophily) * np.eye(dim)
                w = np.linalg.solve(left, b[at].T).T
                if (known := label >= 0).any():
                    w[known] = np.linalg.solve(left + margin * u @ u.T, (b[at[known]] + margin * u.T[label[known]]).T).T
            if after:
                there = np.isin(node, ctx.ids)
                unit = lambda m: m / np.maximum(np.sqrt((m**2).sum(axis=1, keepdims=True)), 1e-12)
                yield _passed(node[there], np.concatenate([unit(w[there]), unit(h[at[there]])], axis=1))
                continue
            if listed:
                yield _passed(node, w)
            whole = np.zeros((len(links.ids), dim), order="F") if whole is None else whole
            whole[at] = w
            ww += w.T @ w
            if classes:
                k = label >= 0
                own += w[k].T @ w[k]
                each += summed(label[k], w[k], classes)
        if seen and not after:
            y, rows = np.empty((len(ctx.features), dim)), links.rows
            for c in range(dim):
                z = links.back(whole[:, c], rows)
                z += links.back(z, rows)
                z = z if len(ctx.ids) == len(links.ids) else z[np.searchsorted(links.ids, ctx.ids)]
                y[:, c] = ctx.back(z[:, None] / 2)[:, 0]
            sums = np.concatenate([y, ww, own, each])
            yield pa.RecordBatch.from_arrays([pa.array([0], pa.int64()), pa.array([[]], pa.list_(pa.float64())), pa.array([np.ascontiguousarray(sums).tobytes()], pa.binary())], ["node", "w", "sums"])

    return run


def _passed(node: np.ndarray, w: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(node), lists_of(w), pa.nulls(len(node), pa.binary())], ["node", "w", "sums"])


def _matrix_of(vectors: DataFrame, ids: np.ndarray, dim: int) -> np.ndarray:
    """Vectors as rows in the order of ids; zero where there is none."""
    out, t = np.zeros((len(ids), dim), order="F"), vectors.select("node", "w").toArrow()
    for batch in t.to_batches():
        out[np.searchsorted(ids, batch.column(0).to_numpy())] = batch.column(1).flatten().to_numpy().reshape(-1, dim)
    return out


def _gram_of_contexts(spark, ctx: Contexts, slices: int = 12, block: int = 4096) -> np.ndarray:
    """Transposed content times content, by blocks of contexts whose rows are written out."""

    def part(x: Contexts, i: int) -> np.ndarray:
        n, f = len(x.ids), len(x.features)
        out = np.zeros((f, f))
        for a in range(n * i // slices, n * (i + 1) // slices, block):
            e = min(a + block, n * (i + 1) // slices)
            m, lo, hi = np.zeros((e - a, f)), x.start[a], x.start[e]
            m[np.repeat(np.arange(e - a), np.diff(x.start[a : e + 1])), x.feature[lo:hi]] = x.value[lo:hi]
            out += m.T @ m
        return out

    return sum(_sliced(spark, ctx, part, slices))


def _fit_squared_by_joins(edges: DataFrame, content: DataFrame, dim: int, reg: float, rounds: int, homophily: float, labels: DataFrame | None, margin: float, seed: int) -> DataFrame:
    """The same by joins of the two-hop pairs, where the transition is too large to be sent."""
    spark = edges.sparkSession
    mean = settle(two_hop_mean(transition(edges)).select(F.col("src").alias("node"), F.col("dst").alias("context"), F.col("value").alias("cnt")), "two-hop")
    ctx = gather_contexts(mean, content, dim)
    if ctx is None or len(ctx.features) > 8000:
        raise ValueError("the content side is too large for the closed form")
    node_vec = settle(init_vectors(mean.select("node").distinct(), "node", "node", dim, dim**-0.5, seed), "nodes")
    gram = _content_gram(content, ctx)
    s = _feature_solution(mean, node_vec, ctx, gram, dim, reg)
    d = degrees(edges).select("node", "strength")
    classes = [r.label for r in labels.select("label").distinct().orderBy("label").collect()] if labels is not None and margin else []
    u = np.zeros((dim, len(classes)))
    for _ in range(rounds):
        h = ctx.dictionary(s)
        h_frame = spark.createDataFrame(pa.table({"context": pa.array(ctx.ids), "h": pa.array(list(h), pa.list_(pa.float64()))}))
        right = mean.join(h_frame, "context").select("node", F.expr("transform(h, x -> x * cnt)").alias("v")).groupBy("node").agg(F.array(*[F.sum(F.col("v")[i]) for i in range(dim)]).alias("b"))
        if homophily:
            pull = edges.join(node_vec.select(F.col("node").alias("dst"), "w"), "dst").select(F.col("src").alias("node"), F.expr("transform(w, x -> x * weight)").alias("v"))
            pull = pull.groupBy("node").agg(F.array(*[F.sum(F.col("v")[i]) for i in range(dim)]).alias("near"))
            right = right.join(pull, "node", "left").join(d, "node", "left")
        else:
            right = right.withColumn("near", F.lit(None).cast("array<double>")).withColumn("strength", F.lit(0.0))
        right = right.join(labels, "node", "left") if classes else right.withColumn("label", F.lit(None).cast("string"))
        a = h.T @ h + reg * np.eye(dim)
        node_vec = settle(right.select("node", "b", "near", "strength", "label").mapInArrow(_solve_nodes(a, u, classes, homophily, margin, dim), "node long, w array<double>"), "nodes")
        if classes:
            u = _classifier(node_vec, labels, classes, dim, reg)
        s = _feature_solution(mean, node_vec, ctx, gram, dim, reg)
    h = ctx.dictionary(s)
    h_frame = spark.createDataFrame(pa.table({"node": pa.array(ctx.ids), "h": pa.array(list(h), pa.list_(pa.float64()))}))
    unit = lambda c: F.expr(f"transform({c}, x -> x / greatest(sqrt(aggregate({c}, CAST(0 AS DOUBLE), (t, y) -> t + y * y)), 1e-12))")
    return node_vec.join(h_frame, "node").select("node", F.concat(unit("w"), unit("h")).alias("w"))


def _solve_nodes(a: np.ndarray, u: np.ndarray, classes: list[str], homophily: float, margin: float, dim: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = {c: i for i, c in enumerate(classes)}
        for batch in batches:
            b = np.array(batch.column(1).to_pylist(), float).reshape(-1, dim)
            if not len(b):
                continue
            left = np.repeat(a[None], len(b), axis=0)
            if homophily:
                near = np.array([x if x is not None else [0.0] * dim for x in batch.column(2).to_pylist()], float)
                strength = np.array([x or 0.0 for x in batch.column(3).to_pylist()], float)
                # a node's pull counts its neighbours' mean, so hubs are not pulled harder
                share = homophily / np.maximum(strength, 1e-12)
                b = b + near * share[:, None]
                left = left + homophily * (strength > 0)[:, None, None] * np.eye(dim)
            for i, label in enumerate(batch.column(4).to_pylist()):
                if label in number:
                    left[i] += margin * u @ u.T
                    b[i] += margin * u[:, number[label]]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(list(np.linalg.solve(left, b[..., None])[..., 0]), pa.list_(pa.float64()))], ["node", "w"])

    return run


def _content_gram(content: DataFrame, ctx: Contexts) -> np.ndarray:
    """Transposed content times content: one aggregation over the pairs of features that a context has."""
    used = settle(content.join(content.sparkSession.createDataFrame(pa.table({"node": pa.array(ctx.ids)})), "node", "left_semi").select("node", "feature", "value"), "gram")
    other = used.select("node", F.col("feature").alias("other"), F.col("value").alias("v2"))
    t = used.join(other, "node").groupBy("feature", "other").agg(F.sum(F.col("value") * F.col("v2")).alias("g")).toArrow()
    n = len(ctx.features)
    out = np.zeros((n, n))
    i, j = (np.searchsorted(ctx.features, t.column(k).to_numpy()) for k in (0, 1))
    out[i, j] = t.column(2).to_numpy()
    return out


def _feature_solution(mean: DataFrame, node_vec: DataFrame, ctx: Contexts, gram: np.ndarray, dim: int, reg: float) -> np.ndarray:
    """The feature embedding that fits best: contexts' sums of node vectors are made by a join, features × dim are solved for."""
    joined = mean.join(node_vec, "node")
    y = joined.select("context", F.expr("transform(w, x -> x * cnt)").alias("v")).groupBy("context").agg(F.array(*[F.sum(F.col("v")[i]) for i in range(dim)]).alias("y")).orderBy("context").toArrow()
    full = np.zeros((len(ctx.ids), dim))
    full[np.searchsorted(ctx.ids, y.column(0).to_numpy())] = np.array(y.column(1).to_pylist(), float).reshape(-1, dim)
    ww = _gram_of(node_vec, dim)
    left = np.linalg.solve(gram + reg * np.eye(len(gram)), ctx.back(full))
    return np.linalg.solve(ww + reg * np.eye(dim), left.T).T


def _gram_of(node_vec: DataFrame, dim: int) -> np.ndarray:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((dim, dim))
        for batch in batches:
            w = np.array(batch.column(0).to_pylist(), float).reshape(-1, dim)
            total += w.T @ w
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(dim)), pa.array(list(total), pa.list_(pa.float64()))], ["i", "g"])

    rows = node_vec.select("w").mapInArrow(run, "i long, g array<double>").groupBy("i").agg(F.array(*[F.sum(F.col("g")[i]) for i in range(dim)]).alias("g")).orderBy("i").collect()
    return np.array([r.g for r in rows], float).reshape(dim, dim)


def _classifier(node_vec: DataFrame, labels: DataFrame, classes: list[str], dim: int, reg: float) -> np.ndarray:
    """Least squares of the labelled nodes' classes, from two sums over them."""
    d = settle(node_vec.join(labels, "node").select("label", "w"), "labelled")
    sums = {r.label: r.s for r in d.groupBy("label").agg(F.array(*[F.sum(F.col("w")[i]) for i in range(dim)]).alias("s")).collect()}
    y = np.array([sums.get(c, [0.0] * dim) for c in classes]).T
    return np.linalg.solve(_gram_of(d, dim) + reg * np.eye(dim), y)


# --- on the driver, up to max_nodes ------------------------------------------------------------------------------------


@dataclass
class SmallGraph:
    ids: np.ndarray
    adjacency: np.ndarray
    content: np.ndarray
    labels: list[str | None]

    @property
    def propagated(self) -> np.ndarray:
        """Adjacency with self loops, over the roots of both degrees."""
        a = self.adjacency + np.eye(len(self.ids))
        r = a.sum(axis=1) ** -0.5
        return a * r[:, None] * r[None, :]


def small_graph(edges: DataFrame, content: DataFrame, labels: DataFrame | None, max_nodes: int) -> SmallGraph:
    names = content.select("node").unionByName(edges.select(F.col("src").alias("node"))).distinct()
    if (n := names.count()) > max_nodes:
        raise ValueError(f"{n} nodes; this method takes {max_nodes} at most")
    ids = names.orderBy("node").toArrow().column(0).to_numpy()
    e, c = edges.select("src", "dst", "weight").toArrow(), content.select("node", "feature", "value").toArrow()
    a = np.zeros((n, n))
    a[np.searchsorted(ids, e.column(0).to_numpy()), np.searchsorted(ids, e.column(1).to_numpy())] = e.column(2).to_numpy()
    features, at = np.unique(c.column(1).to_numpy(), return_inverse=True)
    x = np.zeros((n, len(features)))
    x[np.searchsorted(ids, c.column(0).to_numpy()), at] = c.column(2).to_numpy()
    known = {r.node: r.label for r in labels.select("node", "label").collect()} if labels is not None else {}
    return SmallGraph(ids, a, x, [known.get(int(i)) for i in ids])


def sparse_graph(edges: DataFrame, content: DataFrame, max_nodes: int) -> tuple[np.ndarray, ...]:
    """Ids, edges as places of both ends in order, content as lists (start of each node's, feature's place, value), features."""
    names = content.select("node").unionByName(edges.select(F.col("src").alias("node"))).distinct()
    if (n := names.count()) > max_nodes:
        raise ValueError(f"{n} nodes; this method takes {max_nodes} at most")
    ids = names.orderBy("node").toArrow().column(0).to_numpy()
    e = edges.filter("weight <> 0").select("src", "dst").distinct().toArrow()
    src, dst = (np.searchsorted(ids, e.column(i).to_numpy()) for i in (0, 1))
    order = np.lexsort((dst, src))
    c = content.select("node", "feature", "value").orderBy("node", "feature").toArrow()
    node, feature, value = (c.column(i).to_numpy() for i in range(3))
    features, at = np.unique(feature, return_inverse=True)
    return ids, src[order], dst[order], np.searchsorted(node, np.append(ids, ids[-1:] + 1)), at, value, features


def _vectors(edges: DataFrame, ids: np.ndarray, w: np.ndarray) -> DataFrame:
    return edges.sparkSession.createDataFrame(pa.table({"node": pa.array(ids.astype(np.int64)), "w": pa.array(list(w.astype(float)), pa.list_(pa.float64()))}))


def _cosines(m: np.ndarray) -> np.ndarray:
    m = m / np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-12)
    return m @ m.T


def fit_spectral_fusion(edges: DataFrame, content: DataFrame, labels: DataFrame, dim: int = 16, max_nodes: int = 3000) -> DataFrame:
    """Top eigenvectors of the summed affinities of structure, content and labels, each normalised. Quadratic space, cubic
    time: the reason for max_nodes."""
    g = small_graph(edges, content, labels, max_nodes)
    y = np.array([[float(a is not None and a == b) for b in g.labels] for a in g.labels])
    total = np.zeros_like(g.adjacency)
    for m in (_cosines(g.adjacency), _cosines(g.content), y):
        m = np.maximum(m, 0)
        r = np.maximum(m.sum(axis=1), 1e-12) ** -0.5
        total += m * r[:, None] * r[None, :]
    values, vectors = np.linalg.eigh(total)
    return _vectors(edges, g.ids, vectors[:, -dim:] * np.sqrt(np.maximum(values[-dim:], 0)))


def _adam(params: list[np.ndarray], grads, epochs: int, rate: float) -> None:
    m, v = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
    for t in range(1, epochs + 1):
        for i, g in enumerate(grads(t)):
            m[i] = 0.9 * m[i] + 0.1 * g
            v[i] = 0.999 * v[i] + 0.001 * g * g
            params[i] -= rate * (m[i] / (1 - 0.9**t)) / (np.sqrt(v[i] / (1 - 0.999**t)) + 1e-8)


def _softmax(z: np.ndarray) -> np.ndarray:
    z = np.exp(z - z.max(axis=1, keepdims=True))
    return z / z.sum(axis=1, keepdims=True)


def fit_graph_conv(edges: DataFrame, content: DataFrame, labels: DataFrame, hidden: int = 16, epochs: int = 200, rate: float = 0.01, decay: float = 5e-4, seed: int = 7, max_nodes: int = 5000) -> DataFrame:
    """Two graph convolutions: softmax(P relu(P X W0) W1), P the propagated adjacency. (node, predicted) of all nodes."""
    g = small_graph(edges, content, labels, max_nodes)
    classes = sorted({x for x in g.labels if x is not None})
    train = np.array([i for i, x in enumerate(g.labels) if x is not None])
    y = np.array([[float(g.labels[i] == c) for c in classes] for i in train])
    p = g.propagated
    px = p @ (g.content / np.maximum(g.content.sum(axis=1, keepdims=True), 1e-12))
    r = np.random.default_rng(seed)
    w = [r.uniform(-1, 1, s) * np.sqrt(6 / sum(s)) for s in ((px.shape[1], hidden), (hidden, len(classes)))]

    def grads(_):
        a = px @ w[0]
        h = np.maximum(a, 0)
        ph = p @ h
        out = np.zeros((len(px), len(classes)))
        out[train] = (_softmax((ph @ w[1])[train]) - y) / len(train)
        back = (p.T @ (out @ w[1].T)) * (a > 0)
        return [px.T @ back + decay * w[0], ph.T @ out]

    _adam(w, grads, epochs, rate)
    best = (p @ np.maximum(px @ w[0], 0) @ w[1]).argmax(axis=1)
    return edges.sparkSession.createDataFrame(pa.table({"node": pa.array(g.ids.astype(np.int64)), "predicted": pa.array([classes[i] for i in best])}))


def fit_graph_conv_joins(edges: DataFrame, content: DataFrame, labels: DataFrame, hidden: int = 16, epochs: int = 60, rate: float = 0.01, decay: float = 5e-4, seed: int = 7, max_features: int = 100_000) -> DataFrame:
    """fit_graph_conv for graphs of any size: propagation by joins, weights (features × hidden, hidden × classes) on the driver.

    Only the labelled nodes have a loss, so an epoch reads their edges and the content propagated to their neighbours; sums of
    gradients are made on each task before they come to the driver.
    """
    spark = edges.sparkSession
    known = settle(labels.select("node", "label"), "known")
    classes = [r.label for r in known.select("label").distinct().orderBy("label").collect()]
    features = np.sort(content.select("feature").distinct().toArrow().column(0).to_numpy())
    if len(features) > max_features:
        raise ValueError(f"{len(features)} features; their weights are kept on the driver up to {max_features}")
    nodes = settle(content.select("node").unionByName(edges.select(F.col("src").alias("node"))).distinct(), "nodes")
    strength = settle(nodes.join(degrees(edges), "node", "left").select("node", (1 + F.coalesce("strength", F.lit(0.0))).alias("d")), "strengths")
    loops = edges.select("src", "dst", "weight").unionByName(nodes.select(F.col("node").alias("src"), F.col("node").alias("dst"), F.lit(1.0).alias("weight")))
    p = loops.join(strength.select(F.col("node").alias("src"), F.col("d").alias("a")), "src").join(strength.select(F.col("node").alias("dst"), F.col("d").alias("b")), "dst")
    p = settle(p.groupBy("src", "dst").agg((F.sum("weight") / F.sqrt(F.first("a") * F.first("b"))).alias("p")), "propagation")
    numbers = spark.createDataFrame(pa.table({"feature": pa.array(features), "at": pa.array(np.arange(len(features)))}))
    shares = content.join(content.groupBy("node").agg(F.greatest(F.sum("value"), F.lit(1e-12)).alias("all")), "node").join(numbers, "feature").select(F.col("node").alias("dst"), "at", (F.col("value") / F.col("all")).alias("x"))
    px = p.join(shares, "dst").groupBy(F.col("src").alias("node"), "at").agg(F.sum(F.col("p") * F.col("x")).alias("x")).groupBy("node").agg(F.sort_array(F.collect_list(F.struct("at", "x"))).alias("l"))
    rows = settle(nodes.join(px, "node", "left").select("node", F.coalesce(F.col("l.at"), F.array().cast("array<long>")).alias("at"), F.coalesce(F.col("l.x"), F.array().cast("array<double>")).alias("x")), "content")
    train = settle(p.join(known.select(F.col("node").alias("src")), "src", "left_semi"), "train-edges")
    near = settle(rows.join(train.select(F.col("dst").alias("node")).distinct(), "node", "left_semi"), "near")
    n_train = known.join(nodes, "node", "left_semi").count()
    r = np.random.default_rng(seed)
    w = [r.uniform(-1, 1, s) * np.sqrt(6 / sum(s)) for s in ((len(features), hidden), (hidden, len(classes)))]

    def sparse(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        at, x = (batch.column(i) for i in (1, 2))
        owner = np.repeat(np.arange(batch.num_rows), [len(v) for v in at])
        return owner, at.flatten().to_numpy(zero_copy_only=False), x.flatten().to_numpy(zero_copy_only=False)

    def hidden_of(rows: DataFrame, w0: np.ndarray) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                owner, at, x = sparse(batch)
                h = np.maximum(summed(owner, w0[at] * x[:, None], batch.num_rows), 0)
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(list(h), pa.list_(pa.float64()))], ["node", "h"])

        return rows.mapInArrow(run, "node long, h array<double>")

    def spread(p: DataFrame, vectors: DataFrame, source: str, target: str, dim: int) -> DataFrame:
        """vectors(node, v) sent along p from source to target and summed there."""
        d = p.join(vectors.withColumnRenamed("node", source), source).select(F.col(target).alias("node"), F.expr("transform(v, z -> z * p)").alias("v"))
        return d.groupBy("node").agg(vec_sum("v", dim).alias("v"))

    def grads(_) -> list[np.ndarray]:
        w0, w1 = w[0].copy(), w[1].copy()
        ph = spread(train, hidden_of(near, w0).withColumnRenamed("h", "v"), "dst", "src", hidden).join(known, "node")

        def errors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            number, total = {c: i for i, c in enumerate(classes)}, np.zeros_like(w1)
            for batch in batches:
                v = np.array(batch.column(1).to_pylist(), float).reshape(-1, hidden)
                out = _softmax(v @ w1)
                out[np.arange(len(v)), [number[c] for c in batch.column(2).to_pylist()]] -= 1
                out /= n_train
                total += v.T @ out
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(list(out @ w1.T), pa.list_(pa.float64()))], ["node", "v"])
            yield pa.RecordBatch.from_arrays([pa.array([None], pa.int64()), pa.array([total.ravel()], pa.list_(pa.float64()))], ["node", "v"])

        sent = settle(ph.select("node", "v", "label").mapInArrow(errors, "node long, v array<double>"), "errors")
        g1 = sent.filter("node IS NULL").agg(vec_sum("v", w1.size).alias("g")).first().g
        back = spread(train, sent.filter("node IS NOT NULL"), "src", "dst", hidden)

        def content_sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = np.zeros_like(w0)
            for batch in batches:
                owner, at, x = sparse(batch)
                b = np.array(batch.column(3).to_pylist(), float).reshape(-1, hidden)
                b = b * (summed(owner, w0[at] * x[:, None], batch.num_rows) > 0)
                total += summed(at, b[owner] * x[:, None], len(w0))
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(w0))), pa.array(list(total), pa.list_(pa.float64()))], ["at", "g"])

        parts = near.join(back, "node").select("node", "at", "x", "v").mapInArrow(content_sums, "at long, g array<double>")
        found = {r.at: r.g for r in parts.groupBy("at").agg(vec_sum("g", hidden).alias("g")).collect()}
        g0 = np.array([found.get(i, [0.0] * hidden) for i in range(len(w0))]).reshape(w0.shape)
        return [g0 + decay * w0, np.array(g1 or [0.0] * w1.size).reshape(w1.shape)]

    _adam(w, grads, epochs, rate)
    w1 = w[1].copy()

    def best(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            v = np.array(batch.column(1).to_pylist(), float).reshape(-1, hidden)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([classes[i] for i in (v @ w1).argmax(axis=1)], pa.string())], ["node", "predicted"])

    return spread(p, hidden_of(rows, w[0].copy()).withColumnRenamed("h", "v"), "dst", "src", hidden).mapInArrow(best, "node long, predicted string")


def fit_context_label_mlp(edges: DataFrame, content: DataFrame, labels: DataFrame, dim: int = 16, epochs: int = 200, rate: float = 0.02, seed: int = 7, max_nodes: int = 5_000_000, samples: int = 4000) -> tuple[DataFrame, DataFrame]:
    """A hidden layer from content that predicts sampled contexts (neighbours and nodes of the same label, against random
    ones) and, with the content, the label. -> vectors, (node, predicted).

    Edges and content are kept as lists, so the driver's memory grows with them and with nodes × dim. An epoch reads the
    content of the sampled and the labelled nodes alone.
    """
    spark = edges.sparkSession
    ids, src, dst, start, at, value, features = sparse_graph(edges, content, max_nodes)
    known = {r.node: r.label for r in labels.select("node", "label").collect() if r.label is not None}
    train = np.flatnonzero(np.isin(ids, np.array(sorted(known), ids.dtype)))
    own = [known[int(ids[i])] for i in train]
    classes = sorted(set(own))
    y = np.array([[float(x == c) for c in classes] for x in own]).reshape(len(train), len(classes))
    n, f, k = len(ids), len(features), len(classes)
    length = np.sqrt(np.bincount(np.repeat(np.arange(n), np.diff(start)), value**2, n))
    value = value / np.maximum(np.repeat(length, np.diff(start)), 1e-12)
    r = np.random.default_rng(seed)
    groups = [train[[x == c for x in own]] for c in classes]
    w = [r.normal(0, 0.1, (f, dim)), r.normal(0, 0.1, (n, dim)), r.normal(0, 0.1, (dim, k)), r.normal(0, 0.1, (f, k))]

    def entries(nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Content of the nodes: each entry's place in nodes, feature and value."""
        sizes = start[nodes + 1] - start[nodes]
        owner = np.repeat(np.arange(len(nodes)), sizes)
        e = np.arange(len(owner)) + np.repeat(start[nodes] - (np.cumsum(sizes) - sizes), sizes)
        return owner, at[e], value[e]

    def times(nodes: np.ndarray, m: np.ndarray) -> np.ndarray:
        owner, feature, v = entries(nodes)
        return summed(owner, m[feature] * v[:, None], len(nodes))

    def back(nodes: np.ndarray, g: np.ndarray) -> np.ndarray:
        owner, feature, v = entries(nodes)
        return summed(feature, g[owner] * v[:, None], f)

    def grads(_):
        e = r.integers(0, len(src), samples) if len(src) else np.zeros(0, int)
        a, b = src[e], dst[e]
        same = [(r.choice(m), r.choice(m)) for m in groups if len(m) > 1 for _ in range(samples // (8 * max(1, k)))]
        a, b = np.concatenate([a, [i for i, _ in same]]).astype(int), np.concatenate([b, [j for _, j in same]]).astype(int)
        a, b, t = np.concatenate([a, a]), np.concatenate([b, r.integers(0, n, len(b))]), np.concatenate([np.ones(len(b)), np.zeros(len(b))])
        met, where = np.unique(np.concatenate([a, train]), return_inverse=True)
        a, trained = where[: len(a)], where[len(a) :]
        h = np.tanh(times(met, w[0]))
        d = (0.5 * (1 + np.tanh(0.5 * np.einsum("ij,ij->i", h[a], w[1][b]))) - t) / max(1, len(t))
        gh, gc = summed(a, d[:, None] * w[1][b], len(met)), summed(b, d[:, None] * h[a], n)
        out = (_softmax(h[trained] @ w[2] + times(train, w[3])) - y) / len(train)
        gh[trained] += out @ w[2].T
        return [back(met, gh * (1 - h * h)), gc, h[trained].T @ out, back(train, out)]

    _adam(w, grads, epochs, rate)
    everyone = np.arange(n)
    h = np.tanh(times(everyone, w[0]))
    best = (h @ w[2] + times(everyone, w[3])).argmax(axis=1)
    pred = spark.createDataFrame(pa.table({"node": pa.array(ids.astype(np.int64)), "predicted": pa.array([classes[i] for i in best])}))
    return _vectors(edges, ids, h), pred


def content_vectors(content: DataFrame, features: int) -> DataFrame:
    """Raw content as vectors, for classifiers on content alone."""
    pairs = content.groupBy("node").agg(F.map_from_entries(F.collect_list(F.struct(F.col("feature").cast("int"), "value"))).alias("m"))
    return pairs.select("node", F.expr(f"transform(sequence(0, {features - 1}), i -> coalesce(m[i], CAST(0 AS DOUBLE)))").alias("w"))

