"""Pair counts from walks and from labels."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .checkpoints import settle
from .config import WalkConfig
from .randomness import SPAN, draw, fast_draw
from .ranks import ranked_within


def window_pairs(walks: DataFrame, cfg: WalkConfig = WalkConfig(), oracle: bool = False, pairs_per_walk: int = 1) -> DataFrame:
    """(node, context) rows, forward: every pair in the window, or drawn ones."""
    u = draw if oracle else fast_draw
    steps = ", ".join(map(str, cfg.offsets))
    if cfg.pair_mode == "all":
        each = f"flatten(transform(array({steps}), k -> IF(size(path) > k, transform(sequence(0, size(path) - 1 - k), i -> struct(path[i] AS node, path[i + k] AS context)), array())))"
        return walks.select(F.explode(F.expr(each)).alias("p")).select("p.*")
    w = walks.select("walk_id", "path", F.explode(F.sequence(F.lit(0), F.lit(pairs_per_walk - 1))).alias("no"))
    share = lambda name: u(cfg.seed, F.lit(name), F.col("walk_id"), F.col("no")) / F.lit(float(SPAN))
    if cfg.pair_mode == "offset_uniform":
        w = w.withColumn("k", F.element_at(F.array(*map(F.lit, cfg.offsets)), (F.floor(share("offset") * len(cfg.offsets)) + 1).cast("int")))
        w = w.filter(F.size("path") > F.col("k")).withColumn("i", F.floor(share("place") * (F.size("path") - F.col("k"))).cast("int"))
    else:
        # number all pairs by offset, then place; the drawn number's offset is the first whose pairs reach beyond it
        ends = f"transform(array({steps}), k -> aggregate(filter(array({steps}), j -> j <= k), 0, (s, j) -> s + greatest(size(path) - j, 0)))"
        w = w.withColumn("ends", F.expr(ends)).withColumn("n", F.floor(share("pair") * F.element_at("ends", -1)).cast("int"))
        w = w.withColumn("at", F.expr("size(filter(ends, e -> e <= n))"))
        w = w.withColumn("k", F.expr(f"array({steps})[at]")).withColumn("i", F.expr("n - IF(at = 0, 0, ends[greatest(at, 1) - 1])"))
    return w.select(F.expr("path[i]").alias("node"), F.expr("path[i + k]").alias("context"))


def count_pairs(walks: DataFrame, cfg: WalkConfig = WalkConfig(), oracle: bool = False, pairs_per_walk: int = 1) -> DataFrame:
    """cooc(node, context, cnt). Counts are summed on each task before they are dealt out; of both directions, a pair is dealt
    out once, in the order of its ends, and mirrored afterwards."""
    pairs = window_pairs(walks, cfg, oracle, pairs_per_walk)
    if cfg.direction == "forward":
        return pairs.groupBy("node", "context").agg(F.count("*").alias("cnt"))
    one = pairs.groupBy(F.least("node", "context").alias("a"), F.greatest("node", "context").alias("b")).agg(F.count("*").alias("cnt"))
    # a node that meets itself counts in both directions at once
    both = F.when(F.col("a") == F.col("b"), F.expr("array(struct(a AS node, b AS context, 2 * cnt AS cnt))")).otherwise(F.expr("array(struct(a AS node, b AS context, cnt), struct(b AS node, a AS context, cnt))"))
    return one.select(F.explode(both).alias("p")).select("p.*")


def merge_counts(*cooc: DataFrame) -> DataFrame:
    """Counts are additive: the union's sums."""
    both = reduce(DataFrame.unionByName, [c.select("node", "context", "cnt") for c in cooc])
    return both.groupBy("node", "context").agg(F.sum("cnt").alias("cnt"))


def label_pairs(labels: DataFrame, rounds: int, seed: int = 7, symmetric: bool = True, allow_self: bool = False, oracle: bool = False, max_classes: int = 10_000) -> DataFrame:
    """Label context: rounds times, a labelled node is drawn and then another one with its label; cooc counts.

    The first draw picks a class by its share and a rank in it, which is a uniform node; the second picks another rank.
    Ranks meet nodes in an equi join, so no class is held in one place. A class of one node yields nothing.
    """
    spark: SparkSession = labels.sparkSession
    empty = spark.createDataFrame([], "node long, context long, cnt long")
    classes = labels.groupBy("label").agg(F.count("*").alias("n")).orderBy("label").limit(max_classes + 1).collect()
    if len(classes) > max_classes:
        raise ValueError(f"more than {max_classes} classes")
    if not classes or rounds <= 0:
        return empty
    total, tops, names = 0, [], []
    for c in classes:
        total += c.n
        tops.append(total)
        names.append(c.label)
    u = draw if oracle else fast_draw
    part = lambda name: u(seed, F.lit(name), F.col("id")) / F.lit(float(SPAN))
    d = spark.range(rounds).withColumn("x", F.floor(part("first") * total))
    d = d.withColumn("c", F.size(F.filter(F.lit(tops), lambda t: t <= F.col("x"))))
    d = d.withColumn("label", F.element_at(F.lit(names), F.col("c") + 1)).withColumn("n", F.element_at(F.lit([c.n for c in classes]), F.col("c") + 1))
    d = d.withColumn("r1", (F.col("x") - F.expr(f"IF(c = 0, 0, array({', '.join(map(str, tops))})[greatest(c, 1) - 1])")).cast("long"))
    if allow_self:
        d = d.withColumn("r2", F.floor(part("second") * F.col("n")))
    else:
        d = d.filter("n > 1").withColumn("r2", F.floor(part("second") * (F.col("n") - 1))).withColumn("r2", F.expr("IF(r2 >= r1, r2 + 1, r2)"))
    ranks = settle(ranked_within(labels.select("label", "node"), "label", ["node"]).select("label", "node", (F.col("rank") - 1).alias("rank")), "label-ranks")
    one = d.join(ranks.select("label", F.col("node"), F.col("rank").alias("r1")), ["label", "r1"]).join(ranks.select("label", F.col("node").alias("context"), F.col("rank").alias("r2")), ["label", "r2"])
    one = one.groupBy("node", "context").agg(F.count("*").alias("cnt"))
    return merge_counts(one, one.select(F.col("context").alias("node"), F.col("node").alias("context"), "cnt")) if symmetric else one


def expected_label_pairs(labels: DataFrame, rounds: int) -> DataFrame:
    """Expectation of label_pairs without mirror image: rounds / all / (class - 1) for each ordered pair of a class. For
    small label sets: it has the squares of the class sizes."""
    n = labels.agg(F.count("*").alias("all"))
    size = labels.groupBy("label").agg(F.count("*").alias("size"))
    a = labels.join(size, "label")
    b = labels.select("label", F.col("node").alias("context"))
    pairs = a.join(b, "label").filter("node <> context").join(n, how="cross")  # n is one row
    return pairs.select("node", "context", (F.lit(float(rounds)) / F.col("all") / (F.col("size") - 1)).alias("expected"))


def isolated_nodes(nodes: DataFrame, cooc: DataFrame) -> DataFrame:
    """Nodes without a count."""
    return nodes.select("node").join(cooc.select("node").distinct(), "node", "left_anti")
