"""Joint factorization of counts and content under the likelihood of skip-gram with negative sampling.

counts cooc(node, context, cnt), content(node, feature, value). With k negatives, q = k · row · column / all and
x = (content row of the context) · feature embedding · node vector, a pair's loss is (cnt + q) · softplus(x) − cnt · x.
"""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .checkpoints import settle, settled
from .config import FAST, FitConfig
from .cooccur import count_pairs, label_pairs, merge_counts
from .pair_sums import _sliced, context_sums
from .randomness import SPAN, draw, long_unit, normal, numpy_long_unit
from .ranks import ranked

#: Largest context dictionary with its content, in MB, that each worker process holds; beyond, joins do the work.
BROADCAST_MB = 256.0
#: Largest table of node vectors, in MB, that goes to each worker process so that the counts need not be dealt out again.
NODES_MB = 128.0
#: Entries of a dense block of pairs that a task holds at once.
BLOCK = 2_000_000
#: Contexts from which exact negatives of vectors of SUMMED_DIM numbers or fewer are summed as a function of the node's vector.
SUMMED_FROM, SUMMED_DIM = 200_000, 4


# --- counts -----------------------------------------------------------------------------------------------------------


def count_marginals(cooc: DataFrame) -> tuple[DataFrame, DataFrame, int]:
    """row_tot(node, total), col_tot(context, total) and the sum of all counts."""
    rows = cooc.groupBy("node").agg(F.sum("cnt").alias("total"))
    cols = cooc.groupBy("context").agg(F.sum("cnt").alias("total"))
    return rows, cols, cooc.agg(F.sum("cnt")).first()[0] or 0


def pair_cap(cooc: DataFrame, negatives: float = 1.0) -> DataFrame:
    """Stored pairs with product (k · row · column / all) and cap (product + cnt). The cap of the other pairs is the product
    alone; it is never made."""
    rows, cols, total = count_marginals(cooc)
    c = cooc.join(rows.withColumnRenamed("total", "row_tot"), "node").join(cols.withColumnRenamed("total", "col_tot"), "context")
    product = F.lit(float(negatives)) * F.col("row_tot") * F.col("col_tot") / F.lit(float(max(total, 1)))
    return c.select("node", "context", "cnt", product.alias("product"), (product + F.col("cnt")).alias("cap"))


def shifted_pmi(cooc: DataFrame, negatives: float = 1.0) -> DataFrame:
    """ln(cnt · all / (row · column)) − ln k: where the likelihood of each pair alone is greatest."""
    return pair_cap(cooc, negatives).select("node", "context", F.log(F.col("cnt") / F.col("product")).alias("spmi"))


def softplus(x: Column) -> Column:
    return F.greatest(x, F.lit(0.0)) + F.log1p(F.exp(-F.abs(x)))


def sigmoid(x: Column) -> Column:
    return 1 / (1 + F.exp(-x))


def pair_loss(cnt: Column, cap: Column, x: Column) -> Column:
    """Negative log probability of a count under its cap, without the constant."""
    return cap * softplus(x) - cnt * x


def expected_count(cap: Column, x: Column) -> Column:
    return cap * sigmoid(x)


# --- factors ----------------------------------------------------------------------------------------------------------


def init_vectors(ids: DataFrame, column: str, name: str, dim: int, scale: float, seed: int, oracle: bool = False) -> DataFrame:
    """Random vectors by hash of the id. oracle: even draws by md5, which SQL can follow."""
    if oracle:
        values = [(draw(seed, name, F.col(column), i) / F.lit(float(SPAN)) - 0.5) * scale for i in range(dim)]
    else:
        values = [normal(F.lit(seed), F.lit(name), F.col(column), F.lit(i)) * scale for i in range(dim)]
    return ids.select(column, F.array(*values).alias("s" if name == "feature" else "w"))


def vec_sum(column: str, dim: int) -> Column:
    """Aggregate: the sum of arrays, by one sum for each place, so that it is summed on each task first."""
    return F.array(*[F.sum(F.col(column)[i]) for i in range(dim)])


def context_dictionary(content: DataFrame, feat_vec: DataFrame, dim: int) -> DataFrame:
    """ctx_vec(context, h): content times feature embedding, over the stored entries alone."""
    scaled = content.join(feat_vec, "feature").select(F.col("node").alias("context"), F.expr("transform(s, x -> x * value)").alias("v"))
    return scaled.groupBy("context").agg(vec_sum("v", dim).alias("h"))


def embed_content_only(content: DataFrame, feat_vec: DataFrame, dim: int) -> DataFrame:
    """(node, w) of nodes that no walk has seen: their entry of the context dictionary."""
    return context_dictionary(content, feat_vec, dim).select(F.col("context").alias("node"), F.col("h").alias("w"))


# --- the model on blocks ----------------------------------------------------------------------------------------------


@dataclass
class Contexts:
    """The context side: ids, totals and content rows (start, feature number, value), and the features' ids."""

    ids: np.ndarray
    totals: np.ndarray
    start: np.ndarray
    feature: np.ndarray
    value: np.ndarray
    features: np.ndarray
    total: float

    @property
    def rows(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.ids), dtype=np.int32), np.diff(self.start))

    def dictionary(self, s: np.ndarray) -> np.ndarray:
        """Content times s, one row a context."""
        rows = self.rows
        # a column at a time: the entries times all columns are much larger than the result
        return np.stack([np.bincount(rows, c[self.feature] * self.value, len(self.ids)) for c in s.T], axis=1) if s.shape[1] else np.zeros((len(self.ids), 0))

    def back(self, y: np.ndarray) -> np.ndarray:
        """Transposed content times y, one row a feature."""
        rows = self.rows
        return np.stack([np.bincount(self.feature, c[rows] * self.value, len(self.features)) for c in y.T], axis=1) if y.shape[1] else np.zeros((len(self.features), 0))

    @property
    def squares(self) -> np.ndarray:
        """Squared length of each context's content."""
        return np.bincount(self.rows, self.value**2, len(self.ids))


def summed(at: np.ndarray, values: np.ndarray, n: int) -> np.ndarray:
    """Sums of the rows of values with the same number."""
    return np.stack([np.bincount(at, v, n) for v in values.T], axis=1) if values.shape[1] else np.zeros((n, 0))


def gather_contexts(cooc: DataFrame, content: DataFrame, dim: int = 16, limit_mb: float = BROADCAST_MB) -> Contexts | None:
    """The context side on the driver, or None if a worker would hold more than limit_mb with its dictionary of dim columns."""
    cols = settle(cooc.groupBy("context").agg(F.sum("cnt").cast("double").alias("total")), "columns")
    used = settle(content.join(cols.select(F.col("context").alias("node")), "node", "left_semi"), "used-content")
    n, (f, kinds) = cols.count(), used.agg(F.count("*"), F.countDistinct("feature")).first()
    number = np.min_scalar_type(max(kinds - 1, 0))
    if (24 * n + (8 + number.itemsize) * f + 8 * n * dim) / 1e6 > limit_mb:
        return None
    t = cols.orderBy("context").toArrow()
    ids, totals = t.column(0).to_numpy(), t.column(1).to_numpy()
    features = np.sort(used.select("feature").distinct().toArrow().column(0).to_numpy())
    sizes, c = np.zeros(n, np.int64), used.groupBy("node").count().orderBy("node").toArrow()
    sizes[np.searchsorted(ids, c.column(0).to_numpy())] = c.column(1).to_numpy()
    # a column at a time, and the numbers as narrow as they are: the driver holds no row of the content
    in_order = used.orderBy("node", "feature")
    at = [np.searchsorted(features, x.to_numpy()).astype(number) for x in in_order.select("feature").toArrow().column(0).chunks]
    value = in_order.select(F.col("value").cast("double")).toArrow().column(0).to_numpy()
    at = np.concatenate(at) if at else np.zeros(0, number)
    return Contexts(ids, totals, np.concatenate([[0], np.cumsum(sizes)]), at, value, features, float(totals.sum()))


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + np.tanh(0.5 * x))


def _softplus(x: np.ndarray) -> np.ndarray:
    return np.maximum(x, 0) + np.log1p(np.exp(-np.abs(x)))


class Pairs:
    """Counts and negatives of some nodes against all contexts, dense or as a list, and what follows from them.

    Every loss here is cap · phi(x) − cnt · x for each pair. Of a list, the stored pairs come first; draws stand for the
    rest: with sgns a context is drawn by its share of the counts and weighs k · row / draws, otherwise all alike and
    weigh contexts / draws. A draw is a function of (seed, turn, node, number), so no plan changes it.
    """

    def __init__(self, ctx: Contexts, at: list[np.ndarray], cnt: list[np.ndarray], rows: np.ndarray, cfg: FitConfig, nodes: np.ndarray, turn: int):
        self.ctx, self.cfg, self.n = ctx, cfg, len(rows)
        self.squared = cfg.loss == "squared"
        sizes = [len(a) for a in at]
        owner = np.repeat(np.arange(self.n), sizes)
        place, count = (np.concatenate(z) if len(z) else np.zeros(0) for z in (at, cnt))
        place = place.astype(np.int64)
        if self.squared:
            count = count / rows[owner]
        self.constant = np.bincount(owner, 0.5 * count**2, self.n) if self.squared else 0.0
        if cfg.negative_mode == "exact":
            self.owner = None
            self.cnt = np.zeros((self.n, len(ctx.ids)))
            self.cnt[owner, place] = count
            if cfg.loss == "sgns":
                self.cap = self.cnt + (cfg.negatives / max(ctx.total, 1.0)) * rows[:, None] * ctx.totals[None, :]
            else:
                self.cap = np.ones_like(self.cnt) if self.squared else self.cnt + cfg.negatives
            return
        d = cfg.draws_per_node
        u = numpy_long_unit(cfg.seed, turn, nodes[:, None], np.arange(d)[None, :])
        if cfg.loss == "sgns":
            drawn = np.searchsorted(np.cumsum(ctx.totals), np.floor(u * ctx.total), side="right").clip(0, len(ctx.ids) - 1)
            weight = np.repeat(cfg.negatives * rows / d, d)
        else:
            drawn = np.floor(u * len(ctx.ids)).astype(np.int64)
            weight = np.full(self.n * d, len(ctx.ids) / d * (1.0 if self.squared else cfg.negatives))
        self.owner = np.concatenate([owner, np.repeat(np.arange(self.n), d)])
        self.place = np.concatenate([place, drawn])
        self.cnt = np.concatenate([count, np.zeros(len(drawn))])
        # a stored pair's share of the negatives comes from the draws, so its own cap is its count
        self.cap = np.concatenate([np.zeros(len(count)) if self.squared else count, weight])

    @property
    def bound(self) -> float:
        """Largest second derivative of phi."""
        return 1.0 if self.squared else 0.25

    def scores(self, w: np.ndarray, h: np.ndarray) -> np.ndarray:
        return w @ h.T if self.owner is None else np.einsum("ij,ij->i", w[self.owner], h[self.place])

    def residual(self, x: np.ndarray) -> np.ndarray:
        return self.cap * (x if self.squared else _sigmoid(x)) - self.cnt

    def losses(self, x: np.ndarray) -> np.ndarray:
        """Of each node."""
        each = self.cap * (0.5 * x * x if self.squared else _softplus(x)) - self.cnt * x
        return (each.sum(axis=1) if self.owner is None else np.bincount(self.owner, each, self.n)) + self.constant

    def to_nodes(self, g: np.ndarray, h: np.ndarray) -> np.ndarray:
        return g @ h if self.owner is None else summed(self.owner, g[:, None] * h[self.place], self.n)

    def add_to_contexts(self, y: np.ndarray, g: np.ndarray, w: np.ndarray) -> None:
        """y has a row for each dimension, a column for each context."""
        if self.owner is None:
            y += w.T @ g
            return
        for i in range(len(y)):
            y[i] += np.bincount(self.place, g * w[self.owner, i], y.shape[1])

    def capped(self, c: np.ndarray) -> np.ndarray:
        """Sum over contexts of cap · c, of each node."""
        return self.cap @ c if self.owner is None else np.bincount(self.owner, self.cap * c[self.place], self.n)


def node_step(p: Pairs, w: np.ndarray, h: np.ndarray, cfg: FitConfig) -> tuple[np.ndarray, float, float, np.ndarray]:
    """Inner steps of the nodes' subproblems, which are independent: new vectors, loss before and after, last gradient."""
    curve = p.bound * p.capped((h**2).sum(axis=1)) + 2 * cfg.ridge
    safe = 1 / np.maximum(curve, 1e-12)
    step = np.full(len(w), cfg.step_size) if cfg.step == "fixed" else safe
    if cfg.step in ("search", "backtracking"):
        step = 16 * step
    x = p.scores(w, h)
    loss = p.losses(x) + cfg.ridge * (w**2).sum(axis=1)
    first, grad = float(loss.sum()), np.zeros_like(w)
    for _ in range(cfg.max_inner):
        grad = p.to_nodes(p.residual(x), h) + 2 * cfg.ridge * w
        square = (grad**2).sum(axis=1)
        while True:
            new = w - step[:, None] * grad
            x_new = p.scores(new, h)
            loss_new = p.losses(x_new) + cfg.ridge * (new**2).sum(axis=1)
            worse = loss_new > loss - 0.25 * step * square
            if cfg.step in ("fixed", "lipschitz") or not (worse & (step > safe)).any():
                break
            step = np.where(worse, np.maximum(step / 4, safe), step)
        done = loss.sum() - loss_new.sum() <= cfg.tol * 0.1 * abs(loss.sum())
        w, x, loss = new, x_new, loss_new
        if done and cfg.step != "fixed":
            break
    return w, first, float(loss.sum()), grad


def lists_of(rows: np.ndarray) -> pa.Array:
    """The rows of a matrix as an Arrow column of lists."""
    return pa.ListArray.from_arrays(pa.array(np.arange(0, rows.size + 1, max(1, rows.shape[1]), dtype=np.int32)), pa.array(np.ascontiguousarray(rows, float).ravel()))


#: The context dictionary that this worker process made last, by the number of its pass: tasks of a pass share it.
_HELD: dict[str, np.ndarray] = {}


def _held_dictionary(ctx: Contexts, s: np.ndarray, key: str) -> np.ndarray:
    if key not in _HELD:
        _HELD.clear()
        _HELD[key] = ctx.dictionary(s)
    return _HELD[key]


class JointModel:
    """Counts listed by node on the executors, the context side sent to them once, the feature embedding on the driver. Node
    vectors of up to NODES_MB are sent as well, so that a pass reads the lists where they lie; larger ones are joined."""

    def __init__(self, cooc: DataFrame, content: DataFrame, cfg: FitConfig, ctx: Contexts):
        self.spark: SparkSession = cooc.sparkSession
        self.cfg, self.ctx = cfg, ctx
        self.sent = sent = self.spark.sparkContext.broadcast(ctx)
        # lists in the contexts' order, so that sums do not depend on the plan
        entry = F.struct("context", F.col("cnt").cast("double").alias("cnt"))
        listed = cooc.groupBy("node").agg(F.sum("cnt").cast("double").alias("total"), F.sort_array(F.collect_list(entry)).alias("l"))

        def placed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                ends = np.concatenate([[0], np.cumsum(batch.column(2).value_lengths().to_numpy(zero_copy_only=False))]).astype(np.int32)
                at = np.searchsorted(sent.value.ids, batch.column(2).flatten().to_numpy(zero_copy_only=False)).astype(np.int32)
                lists = [pa.ListArray.from_arrays(pa.array(ends), x) for x in (pa.array(at), batch.column(3).flatten())]
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *lists], ["node", "total", "at", "cnt"])

        listed = listed.select("node", "total", F.col("l.context").alias("context"), F.col("l.cnt").alias("cnt"))
        self.counts = settle(listed.mapInArrow(placed, "node long, total double, at array<int>, cnt array<double>"), "counts")
        self.nodes, self.rate = self.counts.count(), 16.0
        self.vectors: tuple = (None, None)

    def _sent_vectors(self, node_vec: DataFrame):
        """Node ids and vectors for the executors; the last ones stay there until others are sent."""
        if self.vectors[0] is not node_vec:
            if self.vectors[1] is not None:
                self.vectors[1].destroy()
            t = node_vec.select("node", "w").orderBy("node").toArrow()
            ids, w = t.column(0).to_numpy(), np.concatenate([np.zeros(0), *[x.flatten().to_numpy() for x in t.column(1).chunks]])
            # nodes are mostly the contexts, which are there already
            ids = None if np.array_equal(ids, self.ctx.ids) else ids
            self.vectors = (node_vec, self.spark.sparkContext.broadcast((ids, w.reshape(t.num_rows, self.cfg.dim))))
        return self.vectors[1]

    def _blocks(self, node_vec: DataFrame, s: np.ndarray, turn: int, f: Callable, end: Callable | None, schema: str, names: list[str], now: bool = True) -> DataFrame:
        """f(pairs, node ids, w, h) of each block of nodes -> arrays of the result's columns; end() gives those of a
        whole partition after its last block. now: the result is used up before the next call, whose vectors replace these."""
        cfg, whole = self.cfg, self.sent
        if now and getattr(self, "last", None) is not None:
            self.last.destroy()
        self.last, key = self.spark.sparkContext.broadcast(s), uuid.uuid4().hex
        part_sent = self.last
        if not now:
            self.last = None
        known = self._sent_vectors(node_vec) if now and self.nodes * 8 * (s.shape[1] + 1) / 1e6 <= NODES_MB else None

        def record(out) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([lists_of(c) if isinstance(c, np.ndarray) and c.ndim > 1 else pa.array(c) for c in out], names)

        def vectors(part: pa.RecordBatch, ctx: Contexts) -> tuple[pa.RecordBatch, np.ndarray]:
            if known is None:
                return part, part.column(4).flatten().to_numpy(zero_copy_only=False).reshape(part.num_rows, -1)
            ids, w = known.value
            ids, node = ctx.ids if ids is None else ids, part.column(0).to_numpy(zero_copy_only=False)
            i = np.minimum(np.searchsorted(ids, node), len(ids) - 1)
            there = ids[i] == node
            return (part, w[i]) if there.all() else (part.filter(pa.array(there)), w[i[there]])

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            ctx, state = whole.value, {}
            for batch in batches:
                h = _held_dictionary(ctx, part_sent.value, key)
                each = len(ctx.ids) if cfg.negative_mode == "exact" else (cfg.draws_per_node + len(batch.column(2).values) // max(1, batch.num_rows)) * h.shape[1]
                rows = max(1, BLOCK // max(1, each))
                for a in range(0, batch.num_rows, rows):
                    part, w = vectors(batch.slice(a, rows), ctx)
                    node, total = (part.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
                    at, cnt = ([x.values.to_numpy(zero_copy_only=False) for x in part.column(i)] for i in (2, 3))
                    out = f(Pairs(ctx, at, cnt, total, cfg, node, turn), node, w, h, state)
                    if end is None:
                        yield record(out)
            if end is not None and state:
                yield record(end(state, ctx))

        if known is None:
            return self.counts.join(node_vec, "node").select("node", "total", "at", "cnt", "w").mapInArrow(run, schema)
        return self.counts.mapInArrow(run, schema)

    def step_nodes(self, node_vec: DataFrame, s: np.ndarray, turn: int = 0) -> tuple[DataFrame, float, float]:
        cfg = self.cfg
        if (made := self._safe_step(node_vec, s)) is not None:
            new = made.select("node", "w")
            return new, made.agg(F.sum("loss")).first()[0] or 0.0, self.node_gradients(new, s, turn).agg(F.sum("loss")).first()[0] or 0.0

        def f(p, node, w, h, state):
            new, before, after, _ = node_step(p, w, h, cfg)
            first = np.zeros(len(node))
            last = np.zeros(len(node))
            first[:1], last[:1] = before, after
            return node, new, first, last

        out = settle(self._blocks(node_vec, s, turn, f, None, "node long, w array<double>, before double, after double", ["node", "w", "before", "after"]), "nodes")
        before, after = out.agg(F.sum("before"), F.sum("after")).first()
        return out.select("node", "w"), before or 0.0, after or 0.0

    def moved_nodes(self, node_vec: DataFrame, s: np.ndarray, turn: int = 0) -> DataFrame:
        """The nodes' half-step where no loss after it is asked for, which would take sums over a box of the new vectors."""
        made = self._safe_step(node_vec, s)
        return self.step_nodes(node_vec, s, turn)[0] if made is None else made.select("node", "w")

    def _safe_step(self, node_vec: DataFrame, s: np.ndarray) -> DataFrame | None:
        """(node, w, loss): vectors after one safe step and the loss before it, or None where that is not what cfg asks for."""
        cfg = self.cfg
        if not self._summed(s) or cfg.step != "lipschitz" or cfg.max_inner != 1 or cfg.ridge or (made := self._summed_gradients(node_vec, s)) is None:
            return None
        return settle(made.withColumn("step", 1 / F.greatest("curve", F.lit(1e-12))).select("node", F.expr("zip_with(w, g, (a, b) -> a - step * b)").alias("w"), "loss"), "nodes")

    def _summed(self, s: np.ndarray) -> bool:
        cfg = self.cfg
        return cfg.negative_mode == "exact" and cfg.loss == "sgns" and s.shape[1] <= SUMMED_DIM and len(self.ctx.ids) >= SUMMED_FROM

    def _summed_gradients(self, node_vec: DataFrame, s: np.ndarray) -> DataFrame | None:
        """(node, w, g, loss, curve) with exact negatives, without looking at each pair: stored pairs add what they have beyond
        the sum over all contexts. None where the vectors are too long for that."""
        ctx, dim = self.ctx, s.shape[1]
        if len(ctx.ids) == 0:
            return None
        ends = node_vec.agg(*[f(F.col("w")[i]) for f in (F.min, F.max) for i in range(dim)]).first()
        h = ctx.dictionary(s)
        made = context_sums(self.spark, h, ctx.totals, np.array(ends[:dim], float), np.array(ends[dim:], float))
        if made is None:
            return None
        rate, squares = self.cfg.negatives / max(ctx.total, 1.0), (h**2).sum(axis=1)
        sent = self.spark.sparkContext.broadcast((*made, h, squares, float(ctx.totals @ squares)))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            grid, table, h, squares, length = sent.value
            for batch in batches:
                if not batch.num_rows:
                    continue
                node, total = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
                at, cnt = (batch.column(i).flatten().to_numpy(zero_copy_only=False) for i in (2, 3))
                w = np.array(batch.column(4).to_pylist(), float).reshape(len(node), -1)
                owner = np.repeat(np.arange(len(node)), batch.column(2).value_lengths().to_numpy(zero_copy_only=False))
                far = grid.read(table, w) * (rate * total)[:, None]
                x = np.einsum("ij,ij->i", w[owner], h[at])
                loss = far[:, 0] + np.bincount(owner, cnt * (_softplus(x) - x), len(node))
                g = far[:, 1:] + summed(owner, (cnt * (_sigmoid(x) - 1))[:, None] * h[at], len(node))
                curve = 0.25 * (rate * total * length + np.bincount(owner, cnt * squares[at], len(node)))
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(4), pa.array(list(g), pa.list_(pa.float64())), pa.array(loss), pa.array(curve)], ["node", "w", "g", "loss", "curve"])

        return self.counts.join(node_vec, "node").select("node", "total", "at", "cnt", "w").mapInArrow(run, "node long, w array<double>, g array<double>, loss double, curve double")

    def node_gradients(self, node_vec: DataFrame, s: np.ndarray, turn: int = 0) -> DataFrame:
        """(node, g, loss) at the given factors."""
        if self._summed(s) and (made := self._summed_gradients(node_vec, s)) is not None:
            return made.select("node", "g", "loss")

        def f(p, node, w, h, state):
            x = p.scores(w, h)
            return node, p.to_nodes(p.residual(x), h), p.losses(x)

        return self._blocks(node_vec, s, turn, f, None, "node long, g array<double>, loss double", ["node", "g", "loss"], now=False)

    def _summed_feature_gradient(self, node_vec: DataFrame, s: np.ndarray, slices: int = 48) -> tuple[np.ndarray, float, float] | None:
        """As feature_gradient with exact negatives, the sums over all nodes as a function of a context's vector. Stored pairs
        add what they have beyond them. None where the vectors are too long for that."""
        ctx, dim, known = self.ctx, s.shape[1], self._sent_vectors(node_vec)
        ids, w = known.value
        ids, h = ctx.ids if ids is None else ids, ctx.dictionary(s)
        t = self.counts.select("node", "total").orderBy("node").toArrow()
        node, totals = t.column(0).to_numpy(), t.column(1).to_numpy()
        if not len(h) or not len(w):
            return None
        at = np.minimum(np.searchsorted(ids, node), len(ids) - 1)
        there = ids[at] == node
        if (made := context_sums(self.spark, w[at[there]], totals[there], h.min(axis=0), h.max(axis=0))) is None:
            return None
        rate, cuts = self.cfg.negatives / max(ctx.total, 1.0), [len(h) * i // slices for i in range(slices + 1)]
        far = np.concatenate(_sliced(self.spark, (*made, h, cuts), lambda x, i: x[0].read(x[1], x[2][x[3][i] : x[3][i + 1]]), slices))
        far *= rate * ctx.totals[:, None]
        # features × dim numbers from here on
        g = np.concatenate([ctx.back(far[:, 1:]), np.full((1, dim), far[:, 0].sum()), np.zeros((1, dim))])
        del t, node, totals, at, there, made, far
        sent, whole, length = self.spark.sparkContext.broadcast(h), self.sent, float(ctx.totals @ ctx.squares)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            ctx, h = whole.value, sent.value
            ids, vectors = known.value
            ids, squares = ctx.ids if ids is None else ids, ctx.squares
            y, loss, curve = np.zeros((dim, len(h))), 0.0, 0.0
            for batch in batches:
                node, total = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
                at, cnt = (batch.column(i).flatten().to_numpy(zero_copy_only=False) for i in (2, 3))
                own = np.minimum(np.searchsorted(ids, node), len(ids) - 1)
                there = ids[own] == node
                w, owner = np.where(there[:, None], vectors[own], 0.0), np.repeat(np.arange(len(node)), batch.column(2).value_lengths().to_numpy(zero_copy_only=False))
                x = np.einsum("ij,ij->i", w[owner], h[at])
                r = cnt * (_sigmoid(x) - 1)
                for i in range(dim):
                    y[i] += np.bincount(at, r * w[owner, i], len(h))
                loss += float((cnt * (_softplus(x) - x))[there[owner]].sum())
                curve += 0.25 * float((rate * total * length + np.bincount(owner, cnt * squares[at], len(node))) @ (w**2).sum(axis=1))
            out = np.concatenate([ctx.back(y.T), np.full((1, dim), loss), np.full((1, dim), curve)])
            yield pa.RecordBatch.from_arrays([pa.array([np.ascontiguousarray(out).tobytes()], pa.binary())], ["found"])

        for row in self.counts.mapInArrow(run, "found binary").toLocalIterator():
            g += np.frombuffer(row.found).reshape(g.shape)
        sent.destroy()
        return g[:-2], float(g[-2, 0]), float(g[-1, 0])

    def feature_gradient(self, node_vec: DataFrame, s: np.ndarray, turn: int = 0) -> tuple[np.ndarray, float, float]:
        """Gradient of the feature embedding, loss and curvature. Each task keeps one contexts × dim sum over all its nodes
        and returns features × dim rows once; these are summed on the executors before they come to the driver."""
        if self._summed(s) and (made := self._summed_feature_gradient(node_vec, s)) is not None:
            return made
        dim = s.shape[1]

        def f(p, node, w, h, state):
            if not state:
                state.update(y=np.zeros((dim, len(h))), squares=p.ctx.squares, loss=0.0, curve=0.0)
            x = p.scores(w, h)
            p.add_to_contexts(state["y"], p.residual(x), w)
            state["loss"] += p.losses(x).sum()
            state["curve"] += p.bound * float(p.capped(state["squares"]) @ (w**2).sum(axis=1))

        def end(state, ctx):
            g = ctx.back(state["y"].T)
            scalars = np.zeros((1, dim + 2))
            scalars[0, :2] = state["loss"], state["curve"]
            return np.arange(-1, len(g)), np.concatenate([scalars, np.pad(g, ((0, 0), (0, 2)))])

        parts = self._blocks(node_vec, s, turn, f, end, "feature long, g array<double>", ["feature", "g"])
        # as numbers, never as rows: there may be as many features as nodes
        g, scalars, found = np.zeros_like(s), np.zeros(2), parts.groupBy("feature").agg(vec_sum("g", dim + 2).alias("g")).toArrow()
        for batch in found.to_batches():
            i, v = batch.column(0).to_numpy(), batch.column(1).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, dim + 2)
            g[i[i >= 0]] = v[i >= 0, :dim]
            scalars += v[i < 0, :2].sum(axis=0)
        return g, float(scalars[0]), float(scalars[1])

    def step_features(self, node_vec: DataFrame, s: np.ndarray, turn: int = 0) -> tuple[np.ndarray, float, float]:
        """Inner steps along the gradient. 'search' and 'backtracking' begin with a multiple of the safe step that goes up
        where the loss agreed at once and down where it did not; the safe step itself is always taken."""
        cfg = self.cfg
        grad, loss, curve = self.feature_gradient(node_vec, s, turn)
        first = loss
        for _ in range(cfg.max_inner):
            safe = 1 / max(curve, 1e-12)
            square, tries = float((grad**2).sum()), 0
            rate = 1.0 if cfg.step in ("fixed", "lipschitz") else self.rate
            while True:
                new = s - (cfg.step_size if cfg.step == "fixed" else rate * safe) * grad
                g, now, c = self.feature_gradient(node_vec, new, turn)
                if rate <= 1 or now <= loss - 0.25 * rate * safe * square:
                    break
                rate, tries = max(rate / 4, 1.0), tries + 1
            if cfg.step in ("search", "backtracking"):
                self.rate = rate * (2 if not tries else 1)
            done = loss - now <= cfg.tol * abs(loss)
            s, grad, curve, loss = new, g, c, now
            if done and cfg.step != "fixed":
                break
        return s, first, loss


@dataclass
class FitResult:
    """node_vec(node, w), feat_vec(feature, s) and the loss of each half-step."""

    node_vec: DataFrame
    feat_vec: DataFrame
    history: list[dict]
    dim: int

    def history_frame(self) -> DataFrame:
        """One row a half-step: loss before and after, by the same draws, pairs that a pass looks at, and seconds."""
        rows = [(h["outer"], h["half"], float(h["before"]), float(h["after"]), int(h["pairs"]), float(h["seconds"])) for h in self.history]
        return self.node_vec.sparkSession.createDataFrame(rows, "outer int, half string, before double, after double, pairs long, seconds double")

    def falls(self, slack: float = 1e-9) -> bool:
        """Whether no half-step has raised the loss."""
        return bool(self.history) and all(h["after"] <= h["before"] + slack * abs(h["before"]) for h in self.history)

    def trained(self, nodes: DataFrame) -> DataFrame:
        """nodes(node) with trained: whether a count has moved the node's vector."""
        return nodes.select("node").join(self.node_vec.select("node", F.lit(True).alias("trained")), "node", "left").fillna(False, ["trained"])

    def complete(self, nodes: DataFrame, content: DataFrame) -> DataFrame:
        """(node, w) of all nodes: those without counts by their content alone."""
        rest = nodes.select("node").join(self.node_vec.select("node"), "node", "left_anti")
        return self.node_vec.unionByName(embed_content_only(content.join(rest, "node", "left_semi"), self.feat_vec, self.dim))


def _features_frame(spark: SparkSession, ctx: Contexts, s: np.ndarray) -> DataFrame:
    return spark.createDataFrame(pa.table({"feature": pa.array(ctx.features.astype(np.int64)), "s": lists_of(s)}))


def initial(cooc: DataFrame, ctx: Contexts, cfg: FitConfig, oracle: bool = False) -> tuple[DataFrame, np.ndarray]:
    """Random factors: node vectors of scale 1/√dim, feature embeddings of scale 0.1."""
    spark = cooc.sparkSession
    nodes = cooc.select("node").distinct()
    node_vec = init_vectors(nodes, "node", "node", cfg.dim, 1.0 if oracle else cfg.dim**-0.5, cfg.seed, oracle)
    ids = spark.createDataFrame(pa.table({"feature": pa.array(ctx.features.astype(np.int64))}))
    rows = init_vectors(ids, "feature", "feature", cfg.dim, 1.0 if oracle else 0.1, cfg.seed, oracle).orderBy("feature").toArrow()
    return settle(node_vec, "initial"), np.concatenate([np.zeros(0), *[x.flatten().to_numpy() for x in rows.column(1).chunks]]).reshape(len(ctx.features), cfg.dim)


def pairs_looked_at(stored: int, nodes: int, contexts: int, cfg: FitConfig) -> int:
    return nodes * contexts if cfg.negative_mode == "exact" else stored + nodes * cfg.draws_per_node


def alternate(model, node_vec, s, cfg: FitConfig, pairs: int) -> tuple:
    """Half-steps of a model until the loss falls by less than tol of itself; -> factors and history. Draws are made anew
    in each half-step and are the same within one, so that its losses can be compared."""
    history: list[dict] = []
    last = None
    for outer in range(cfg.max_outer):
        for turn, half in ((2 * outer, "nodes"), (2 * outer + 1, "features")):
            began = time.time()
            if half == "nodes":
                node_vec, before, after = model.step_nodes(node_vec, s, turn)
            else:
                s, before, after = model.step_features(node_vec, s, turn)
            history.append({"outer": outer, "half": half, "before": before, "after": after, "pairs": pairs, "seconds": time.time() - began})
        if last is not None and abs(last - after) <= cfg.tol * abs(last) and cfg.step != "fixed":
            break
        last = after
    return node_vec, s, history


def fit_joint(cooc: DataFrame, content: DataFrame, cfg: FitConfig = FAST, broadcast_mb: float = BROADCAST_MB) -> FitResult:
    """Alternate between node vectors and feature embedding until the loss falls by less than tol of itself.

    The node half-step is one pass over the counts: nodes are independent given the context dictionary. The feature
    half-step adds one pass for each step. Node vectors are written every time round. Where the context side is over
    broadcast_mb, fit_by_joins does the same by joins, with the same draws; the exact negatives, which look at all pairs
    of nodes and contexts, are refused there.
    """
    cooc = settled(cooc, ["node", "context", "cnt"], "cooc")
    ctx = gather_contexts(cooc, content, cfg.dim, broadcast_mb)
    if ctx is None:
        return fit_by_joins(cooc, content, cfg)
    model = JointModel(cooc, content, cfg, ctx)
    node_vec, s = initial(cooc, ctx, cfg)
    node_vec, s, history = alternate(model, node_vec, s, cfg, pairs_looked_at(cooc.count(), node_vec.count(), len(ctx.ids), cfg))
    return FitResult(node_vec, _features_frame(model.spark, ctx, s), history, cfg.dim)


def fit_counts_only(cooc: DataFrame, cfg: FitConfig = FAST) -> FitResult:
    """No content: each context is its own feature."""
    ids = cooc.select(F.col("context").alias("node")).distinct()
    return fit_joint(cooc, ids.select("node", F.col("node").alias("feature"), F.lit(1.0).alias("value")), cfg)


# --- the model on joins -----------------------------------------------------------------------------------------------


def drawing_table(cooc: DataFrame, cfg: FitConfig) -> tuple[DataFrame, int, int]:
    """(cell, start, end, context), all units and the width of a cell: contexts in their order lie along a line, each as
    long as its count (sgns) or one unit, cut into as many cells as there are contexts. A context has a row for each cell
    it touches, so there are twice as many rows as contexts at most, and a frequent one's draws are spread over its cells."""
    cols = cooc.groupBy("context").agg(F.sum("cnt").cast("long").alias("t"))
    cols = cols if cfg.loss == "sgns" else cols.withColumn("t", F.lit(1).cast("long"))
    line = settle(ranked(cols, ["context"], {"end": "t"}), "line")
    n, total = line.agg(F.count("*"), F.max("end")).first()
    width = max(1, (total or 0) // max(1, n))
    start = F.col("end") - F.col("t")
    table = line.select("context", start.alias("start"), "end").withColumn("cell", F.explode(F.expr(f"sequence(start div {width}, (`end` - 1) div {width})")))
    return settle(table, "cells"), int(total or 0), width


def sampled_pairs(cooc: DataFrame, cfg: FitConfig, turn: int, rows: DataFrame, drawing: tuple[DataFrame, int, int], contexts: int) -> DataFrame:
    """(node, context, cnt, cap, fixed): the pairs that Pairs lists, made by joins. fixed is the squared loss's constant."""
    table, total, width = drawing
    d = rows.withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(cfg.draws_per_node - 1))))
    d = d.withColumn("v", F.floor(long_unit(cfg.seed, turn, F.col("node"), F.col("j")) * float(total)).cast("long")).withColumn("cell", F.expr(f"v div {width}"))
    d = d.join(table, "cell").filter("v >= start AND v < `end`")
    squared = cfg.loss == "squared"
    weight = F.lit(cfg.negatives / cfg.draws_per_node) * F.col("total") if cfg.loss == "sgns" else F.lit(contexts / cfg.draws_per_node * (1.0 if squared else cfg.negatives))
    drawn = d.select("node", "context", F.lit(0.0).alias("cnt"), weight.cast("double").alias("cap"), F.lit(0.0).alias("fixed"))
    cnt = F.col("cnt").cast("double")
    if squared:
        own = cooc.join(rows, "node").select("node", "context", (cnt / F.col("total")).alias("cnt"))
        stored = own.select("node", "context", "cnt", F.lit(0.0).alias("cap"), (F.col("cnt") * F.col("cnt") / 2).alias("fixed"))
    else:
        stored = cooc.select("node", "context", cnt.alias("cnt"), cnt.alias("cap"), F.lit(0.0).alias("fixed"))
    return stored.unionByName(drawn)


def join_scores(pairs: DataFrame, node_vec: DataFrame, ctx_vec: DataFrame) -> DataFrame:
    """pairs with w, h and x."""
    from .evaluate import dot

    return pairs.join(node_vec, "node").join(ctx_vec, "context").withColumn("x", dot("w", "h"))


def grad_nodes(scored: DataFrame, dim: int) -> DataFrame:
    """(node, g, curve) of scored pairs(node, cnt, cap, w, h, x)."""
    r = expected_count(F.col("cap"), F.col("x")) - F.col("cnt")
    d = scored.withColumn("r", r).withColumn("v", F.expr("transform(h, y -> y * r)")).withColumn("c", F.expr("aggregate(h, CAST(0 AS DOUBLE), (s, y) -> s + y * y)") * F.col("cap") / 4)
    return d.groupBy("node").agg(vec_sum("v", dim).alias("g"), F.sum("c").alias("curve"))


def grad_features(scored: DataFrame, content: DataFrame, dim: int) -> DataFrame:
    """(feature, g): contexts' sums first, then spread over their content."""
    r = expected_count(F.col("cap"), F.col("x")) - F.col("cnt")
    y = scored.withColumn("r", r).withColumn("v", F.expr("transform(w, z -> z * r)")).groupBy("context").agg(vec_sum("v", dim).alias("y"))
    d = content.join(y, F.col("node") == F.col("context")).select("feature", F.expr("transform(y, z -> z * value)").alias("v"))
    return d.groupBy("feature").agg(vec_sum("v", dim).alias("g"))


class JoinModel:
    """The same half-steps for context sides of any size: vectors meet pairs by joins, sums are made on each task first, and
    only losses and curvatures come to the driver. The feature embedding is a table, as the node vectors are."""

    def __init__(self, cooc: DataFrame, content: DataFrame, cfg: FitConfig):
        self.cooc, self.content, self.cfg, self.rate = cooc, content, cfg, 16.0
        self.rows = settle(cooc.groupBy("node").agg(F.sum("cnt").alias("total")), "rows")
        self.drawing = drawing_table(cooc, cfg)
        self.contexts = cooc.select("context").distinct().count()
        self.lengths = settle(content.groupBy(F.col("node").alias("context")).agg(F.sum(F.col("value") * F.col("value")).alias("f2")), "lengths")
        self.bound = 1.0 if cfg.loss == "squared" else 0.25
        self.turn: int | None = None

    def pairs(self, turn: int) -> DataFrame:
        if turn != self.turn:
            self.turn, self.made = turn, settle(sampled_pairs(self.cooc, self.cfg, turn, self.rows, self.drawing, self.contexts), "pairs")
        return self.made

    def scored(self, pairs: DataFrame, node_vec: DataFrame, ctx_vec: DataFrame) -> DataFrame:
        x = F.col("x")
        phi, slope = (x * x / 2, x) if self.cfg.loss == "squared" else (softplus(x), sigmoid(x))
        d = join_scores(pairs, node_vec, ctx_vec)
        return d.withColumns({"loss": F.col("cap") * phi - F.col("cnt") * x + F.col("fixed"), "r": F.col("cap") * slope - F.col("cnt")})

    def step_nodes(self, node_vec: DataFrame, feat_vec: DataFrame, turn: int) -> tuple[DataFrame, float, float]:
        cfg, pairs = self.cfg, self.pairs(turn)
        ctx_vec = settle(context_dictionary(self.content, feat_vec, cfg.dim), "contexts")
        w2 = F.expr("aggregate(w, CAST(0 AS DOUBLE), (s, z) -> s + z * z)")
        h2 = F.expr("aggregate(h, CAST(0 AS DOUBLE), (s, z) -> s + z * z)")
        losses = []
        for inner in range(cfg.max_inner + 1):
            d = self.scored(pairs, node_vec, ctx_vec).withColumns({"v": F.expr("transform(h, y -> y * r)"), "c": F.col("cap") * h2 * self.bound})
            g = d.groupBy("node").agg(vec_sum("v", cfg.dim).alias("g"), F.sum("c").alias("curve"), F.sum("loss").alias("loss"))
            d = settle(node_vec.join(g, "node").withColumn("loss", F.col("loss") + cfg.ridge * w2), "node-gradients")
            losses.append(d.agg(F.sum("loss")).first()[0] or 0.0)
            if inner == cfg.max_inner:
                break
            step = F.lit(cfg.step_size) if cfg.step == "fixed" else 1 / F.greatest(F.col("curve") + 2 * cfg.ridge, F.lit(1e-12))
            node_vec = settle(d.withColumn("step", step).select("node", F.expr(f"zip_with(w, g, (a, b) -> a - step * (b + {2 * cfg.ridge!r}D * a))").alias("w")), "nodes")
        return node_vec, losses[0], losses[-1]

    def feature_gradient(self, node_vec: DataFrame, feat_vec: DataFrame, turn: int) -> tuple[DataFrame, float, float, float]:
        """(feature, g), loss, curvature and squared length of the gradient."""
        cfg = self.cfg
        ctx_vec = settle(context_dictionary(self.content, feat_vec, cfg.dim), "contexts")
        w2 = F.expr("aggregate(w, CAST(0 AS DOUBLE), (s, z) -> s + z * z)")
        d = self.scored(self.pairs(turn), node_vec, ctx_vec).join(self.lengths, "context")
        d = d.withColumns({"v": F.expr("transform(w, z -> z * r)"), "c": F.col("cap") * F.col("f2") * w2 * self.bound})
        y = settle(d.groupBy("context").agg(vec_sum("v", cfg.dim).alias("y"), F.sum("loss").alias("loss"), F.sum("c").alias("c")), "context-sums")
        loss, curve = y.agg(F.sum("loss"), F.sum("c")).first()
        back = self.content.join(y.select(F.col("context").alias("node"), "y"), "node").select("feature", F.expr("transform(y, z -> z * value)").alias("v"))
        g = settle(back.groupBy("feature").agg(vec_sum("v", cfg.dim).alias("g")), "feature-gradients")
        square = g.agg(F.sum(F.expr("aggregate(g, CAST(0 AS DOUBLE), (s, z) -> s + z * z)"))).first()[0]
        return g, loss or 0.0, curve or 0.0, square or 0.0

    def step_features(self, node_vec: DataFrame, feat_vec: DataFrame, turn: int) -> tuple[DataFrame, float, float]:
        cfg = self.cfg
        g, loss, curve, square = self.feature_gradient(node_vec, feat_vec, turn)
        first = loss
        for _ in range(cfg.max_inner):
            safe, tries = 1 / max(curve, 1e-12), 0
            rate = 1.0 if cfg.step in ("fixed", "lipschitz") else self.rate
            while True:
                step = cfg.step_size if cfg.step == "fixed" else rate * safe
                new = settle(feat_vec.join(g, "feature", "left").select("feature", F.expr(f"IF(g IS NULL, s, zip_with(s, g, (a, b) -> a - {step!r}D * b))").alias("s")), "features")
                g_new, now, c, q = self.feature_gradient(node_vec, new, turn)
                if rate <= 1 or now <= loss - 0.25 * rate * safe * square:
                    break
                rate, tries = max(rate / 4, 1.0), tries + 1
            if cfg.step == "search":
                self.rate = rate * (2 if not tries else 1)
            done = loss - now <= cfg.tol * abs(loss)
            feat_vec, g, curve, square, loss = new, g_new, c, q, now
            if done and cfg.step != "fixed":
                break
        return feat_vec, first, loss


def fit_by_joins(cooc: DataFrame, content: DataFrame, cfg: FitConfig) -> FitResult:
    """fit_joint for context sides of any size: the same losses, draws and feature steps, by joins. Nodes take the safe (or
    the fixed) step. All pairs and a line search for each node need the context side on the executors, and are refused."""
    if cfg.negative_mode == "exact" or cfg.step == "backtracking":
        raise ValueError("by joins, negatives are sampled and steps are not searched for each node")
    cooc = settled(cooc, ["node", "context", "cnt"], "cooc")
    used = settle(content.join(cooc.select(F.col("context").alias("node")).distinct(), "node", "left_semi"), "used-content")
    model = JoinModel(cooc, used, cfg)
    node_vec = settle(init_vectors(model.rows, "node", "node", cfg.dim, cfg.dim**-0.5, cfg.seed), "nodes")
    feat_vec = settle(init_vectors(used.select(F.col("feature").cast("long").alias("feature")).distinct(), "feature", "feature", cfg.dim, 0.1, cfg.seed), "features")
    node_vec, feat_vec, history = alternate(model, node_vec, feat_vec, cfg, pairs_looked_at(cooc.count(), model.rows.count(), model.contexts, cfg))
    return FitResult(node_vec, feat_vec, history, cfg.dim)


def embed_graph(edges: DataFrame, content: DataFrame | None, walk_cfg=None, fit_cfg: FitConfig = FAST, labels: DataFrame | None = None, label_rounds: int = 0) -> FitResult:
    """Walks, counts, label context and factorization in one call. No content: counts alone."""
    from .config import WalkConfig
    from .walks import sample_walks

    walk_cfg = walk_cfg or WalkConfig()
    cooc = count_pairs(sample_walks(edges, walk_cfg), walk_cfg)
    if labels is not None and label_rounds:
        cooc = merge_counts(cooc, label_pairs(labels, label_rounds, walk_cfg.seed))
    return fit_counts_only(cooc, fit_cfg) if content is None else fit_joint(cooc, content, fit_cfg)
