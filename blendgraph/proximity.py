"""Exact proximities: transition powers, their sum and mean, rooted PageRank, and the gap between both."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .checkpoints import settle
from .links import LINKS_MB, Links, gather_links, ranges


def _times(a: DataFrame, t: DataFrame, least: float = 0.0) -> DataFrame:
    out = a.join(t.select(F.col("src").alias("mid"), F.col("dst").alias("end"), "p"), F.col("dst") == F.col("mid")).groupBy("src", F.col("end").alias("dst")).agg(F.sum(F.col("value") * F.col("p")).alias("value"))
    return out.filter(F.col("value") >= least) if least > 0 else out


def transition_powers(t: DataFrame, order: int, roots: DataFrame | None = None, prune_below: float = 0.0, write_every: int = 3) -> list[DataFrame]:
    """P, P², ... as (src, dst, value). roots(node) keeps only their rows, which makes the work linear in them."""
    first = t.select("src", "dst", F.col("p").alias("value"))
    if roots is not None:
        first = first.join(roots.select(F.col("node").alias("src")), "src", "left_semi")
    out = [first]
    for k in range(1, order):
        nxt = _times(out[-1], t, prune_below)
        out.append(settle(nxt, "power") if k % write_every == 0 else nxt)
    return out


def proximity_sum(t: DataFrame, order: int, roots: DataFrame | None = None, weights: list[float] | None = None) -> DataFrame:
    """Weighted sum of the powers 1..order (weights default to 1)."""
    parts = [p.withColumn("value", F.col("value") * w) for p, w in zip(transition_powers(t, order, roots), weights or [1.0] * order)]
    both = parts[0]
    for p in parts[1:]:
        both = both.unionByName(p)
    return both.groupBy("src", "dst").agg(F.sum("value").alias("value"))


def offset_weights(order: int, weights: str = "uniform", walk_length: int = 40) -> list[float]:
    """Share of each offset: equal, or as walks of walk_length give it when all pairs are counted."""
    raw = [1.0] * order if weights == "uniform" else [float(walk_length - k) for k in range(1, order + 1)]
    return [w / sum(raw) for w in raw]


def expected_cooc(t: DataFrame, order: int, weights: str = "uniform", walk_length: int = 40, roots: DataFrame | None = None) -> DataFrame:
    """Limit of the row-normalised counts under stationary starts."""
    return proximity_sum(t, order, roots, offset_weights(order, weights, walk_length))


def two_hop_mean(t: DataFrame) -> DataFrame:
    """The special case of order 2."""
    return expected_cooc(t, 2)


def rooted_pagerank(t: DataFrame, beta: float, eps: float = 1e-8, roots: DataFrame | None = None, nodes: DataFrame | None = None, links_mb: float = LINKS_MB) -> DataFrame:
    """Power series of rooted PageRank, cut where the rest's mass beta^(T+1) is eps or less. A node without edges keeps 1 - beta.

    Where the transition is of links_mb or less, it goes to the worker processes, and each task makes its roots' whole series; the
    powers of a larger one are joined."""
    if not 0 < beta < 1:
        raise ValueError("beta lies between 0 and 1")
    order = max(1, math.ceil(math.log(eps) / math.log(beta)))
    own = (roots if roots is not None else nodes if nodes is not None else t.select(F.col("src").alias("node")).distinct()).select("node")
    links = gather_links(t, links_mb)
    if links is not None and not (links.entries() == 0).any():
        return _series_of_roots(own, links, beta, order)
    total = own.select(F.col("node").alias("src"), F.col("node").alias("dst"), F.lit(1 - beta).alias("value"))
    power = own.select(F.col("node").alias("src"), F.col("node").alias("dst"), F.lit(1.0).alias("value"))
    for k in range(1, order + 1):
        power = _times(power, t)
        total = total.unionByName(power.withColumn("value", F.col("value") * ((1 - beta) * beta**k)))
        if k % 5 == 0:
            power = settle(power, "series")
            total = settle(total.groupBy("src", "dst").agg(F.sum("value").alias("value")), "series-sum")
    return total.groupBy("src", "dst").agg(F.sum("value").alias("value"))


def _series_of_roots(own: DataFrame, links: Links, beta: float, order: int, most: int = 8_000_000, group: int = 128) -> DataFrame:
    """(src, dst, value) of each root. Roots near each other in their order share what they reach, so a group of them is one
    block of columns over the nodes within `order` hops; a block of over `most` numbers an edge is halved."""
    sent = own.sparkSession.sparkContext.broadcast(links)

    def series(links: Links, place: np.ndarray, roots: np.ndarray) -> Iterator[pa.RecordBatch]:
        reached, edge = roots, roots
        for _ in range(order):
            place[reached] = 0
            new = np.unique(links.at[ranges(links.start[edge], links.start[edge + 1] - links.start[edge])])
            edge = new[place[new] < 0]
            place[reached] = -1
            reached = np.union1d(reached, edge)
        n, sizes = len(reached), links.start[reached + 1] - links.start[reached]
        if len(roots) > 1 and int(sizes.sum()) * len(roots) > most:
            for half in (roots[: len(roots) // 2], roots[len(roots) // 2 :]):
                yield from series(links, place, half)
            return
        at = ranges(links.start[reached], sizes)
        place[reached] = np.arange(n)
        dst, src = place[links.at[at]], np.repeat(np.arange(n), sizes)
        p = links.p[at] if links.values is None else links.values[links.p[at]]
        own = place[roots]
        place[reached] = -1
        # entries that leave the last hop lead to what no power of the series reaches
        inside = np.flatnonzero(dst >= 0)
        inside = inside[np.argsort(dst[inside], kind="stable")]
        dst, src, p = dst[inside], src[inside], p[inside, None]
        first = np.flatnonzero(np.diff(dst, prepend=-1))
        power = np.zeros((n, len(roots)))
        power[own, np.arange(len(roots))] = 1.0
        total = power * (1 - beta)
        for k in range(1, order + 1):
            nxt = np.zeros_like(power)
            if len(first):
                part = power[src]
                part *= p
                nxt[dst[first]] = np.add.reduceat(part, first, axis=0)
            power = nxt
            total += power * ((1 - beta) * beta**k)
        total = total.T
        root, to = np.nonzero(total)
        for a in range(0, len(root), 200_000):
            i, j = root[a : a + 200_000], to[a : a + 200_000]
            yield pa.RecordBatch.from_arrays([pa.array(links.ids[roots[i]]), pa.array(links.ids[reached[j]]), pa.array(total[i, j])], ["src", "dst", "value"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        links, place = sent.value, None
        for batch in batches:
            node = batch.column(0).to_numpy(zero_copy_only=False)
            place = np.full(len(links.ids), -1, np.int64) if place is None else place
            i = np.searchsorted(links.ids, node)
            known = i < len(links.ids)
            known[known] = links.ids[i[known]] == node[known]
            alone = node[~known]
            yield pa.RecordBatch.from_arrays([pa.array(alone), pa.array(alone), pa.array(np.full(len(alone), 1 - beta))], ["src", "dst", "value"])
            for a in range(0, int(known.sum()), group):
                yield from series(links, place, i[known][a : a + group])

    near = own.distinct().repartitionByRange(48, "node").sortWithinPartitions("node")
    return near.mapInArrow(run, "src long, dst long, value double")


def split_index(order: int, beta: float) -> int:
    """Where the series' terms fall below 1 / order."""
    return math.floor(-math.log(order * (1 - beta)) / math.log(beta))


def gap_bounds(order: int, beta: float) -> dict:
    """The bound, what the derivation has before its last step, and whether both apply."""
    k = split_index(order, beta)
    return {"k_split": k, "bound": 2 - 2 * beta ** (k + 1), "pre_bound": 1 - 2 * beta ** (k + 1) + 2 * beta ** (order + 1) + (order - 2 * k) / order, "applicable": order * (1 - beta) >= 1 and order > k}


def dense_rooted_pagerank(p: np.ndarray, beta: float) -> np.ndarray:
    """By the inverse: for small graphs and tests."""
    return (1 - beta) * np.linalg.inv(np.eye(len(p)) - beta * p)


def gap_weights(order: int, beta: float, eps: float = 1e-9) -> list[float]:
    """Weight of each power of the transition, from 0 on, in rooted PageRank less the mean of the first `order` powers."""
    last = max(order, math.ceil(math.log(eps) / math.log(beta)))
    return [(1 - beta) * beta**k - (1 / order if 1 <= k <= order else 0.0) for k in range(last + 1)]


def weighted_powers_times(lists: DataFrame, x: DataFrame, weights: list[float]) -> DataFrame:
    """(i, x): the weighted sum of powers of a matrix, times a vector. lists(i, to) has what entry i gives to others, as
    structs (j, p). No power is formed: a step is one join and one aggregation of vectors, which carry the sum so far."""
    d = x.select("i", "x", (F.col("x") * weights[0]).alias("y"))
    for k, w in enumerate(weights[1:], 1):
        d = d.join(lists, "i", "left")
        d = d.select(F.inline(F.expr("concat(array(struct(i AS i, CAST(0 AS DOUBLE) AS x, y AS y)), transform(coalesce(to, array()), t -> struct(t.j AS i, t.p * x AS x, CAST(0 AS DOUBLE) AS y)))")))
        d = d.groupBy("i").agg(F.sum("x").alias("x"), F.sum("y").alias("y")).select("i", "x", (F.col("y") + F.lit(w) * F.col("x")).alias("y"))
        d = settle(d, "powers") if k % 16 == 0 else d
    return d.select("i", F.col("y").alias("x"))


def powers_norm(t: DataFrame, weights: list[float], rounds: int = 40, tol: float = 1e-6, seed: int = 3) -> float:
    """Largest singular value of the weighted sum of the transition's powers, by power iteration. Work and shuffles are
    linear in the edges; one scalar a round comes to the driver."""
    listed = lambda a, b: settle(t.groupBy(F.col(a).alias("i")).agg(F.sort_array(F.collect_list(F.struct(F.col(b).alias("j"), F.col("p").alias("p")))).alias("to")), "lists")
    # entry dst of a vector gives p to entry src of the product, and the other way round for the transposed one
    forth, back = listed("dst", "src"), listed("src", "dst")
    x = forth.select("i").union(back.select("i")).distinct().withColumn("x", 1.0 + F.pmod(F.xxhash64(F.lit(seed), "i"), F.lit(1000)) / 1000.0)
    last = 0.0
    for _ in range(rounds):
        y = settle(weighted_powers_times(forth, x, weights), "vector")
        z = settle(weighted_powers_times(back, y, weights), "vector")
        norm = math.sqrt(z.agg(F.sum(F.col("x") * F.col("x"))).first()[0] or 0.0)
        if norm == 0:
            return 0.0
        x = z.withColumn("x", F.col("x") / norm)
        if abs(norm - last) <= tol * norm:
            break
        last = norm
    return math.sqrt(norm)


def proximity_gap_dense(t: DataFrame, order: int, beta: float, max_nodes: int = 2000) -> dict:
    """What proximity_gap returns, by matrices on the driver: for small graphs, which it is refused above max_nodes."""
    names = t.select(F.col("src").alias("i")).unionByName(t.select(F.col("dst").alias("i"))).distinct().orderBy("i").limit(max_nodes + 1).collect()
    if len(names) > max_nodes:
        raise ValueError(f"more than {max_nodes} nodes")
    at = {r.i: k for k, r in enumerate(names)}
    p = np.zeros((len(at), len(at)))
    for r in t.select("src", "dst", "p").collect():
        p[at[r.src], at[r.dst]] += r.p
    mean = sum(np.linalg.matrix_power(p, k) for k in range(1, order + 1)) / order
    gap = float(np.linalg.norm(dense_rooted_pagerank(p, beta) - mean, 2))
    return gap_bounds(order, beta) | {"gap": gap, "sigma_max": float(np.linalg.norm(p, 2)), "premise_symmetric": bool(np.allclose(p, p.T)), "order": order, "beta": beta}


def proximity_gap(t: DataFrame, order: int, beta: float, eps: float = 1e-9, rounds: int = 40, tol: float = 1e-6) -> DataFrame:
    """One row: spectral norm of rooted PageRank minus the mean proximity, bounds, the transition's largest singular value and
    whether it is symmetric, which the bound supposes."""
    spark: SparkSession = t.sparkSession
    gap = powers_norm(t, gap_weights(order, beta, eps), rounds, tol)
    sigma = powers_norm(t, [0.0, 1.0], rounds, tol)
    other = t.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.col("p").alias("q"))
    lopsided = t.join(other, ["src", "dst"], "left").filter(F.abs(F.col("p") - F.coalesce("q", F.lit(0.0))) > 1e-12).isEmpty()
    row = gap_bounds(order, beta) | {"gap": gap, "sigma_max": sigma, "premise_symmetric": lopsided, "order": order, "beta": beta}
    return spark.createDataFrame([row], "k_split int, gap double, pre_bound double, bound double, sigma_max double, premise_symmetric boolean, applicable boolean, `order` int, beta double")
