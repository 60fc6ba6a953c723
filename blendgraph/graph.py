"""Edges, transition probabilities, degrees, components and spanning forests."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .checkpoints import settle
from .randomness import fast_draw


def mirrored(edges: DataFrame) -> DataFrame:
    """One row a pair -> both directions."""
    return edges.select("src", "dst", "weight").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight"))


def symmetrize(edges: DataFrame, agg: str = "sum") -> DataFrame:
    """Any edge list -> symmetric, without duplicates and self loops. agg: sum, max or one (all weights 1)."""
    return dedup_edges(mirrored(drop_self_loops(edges)), agg)


def drop_self_loops(edges: DataFrame) -> DataFrame:
    return edges.filter("src <> dst")


def dedup_edges(edges: DataFrame, agg: str = "sum") -> DataFrame:
    how = {"sum": F.sum("weight"), "max": F.max("weight"), "one": F.lit(1.0)}[agg]
    return edges.groupBy("src", "dst").agg(how.alias("weight"))


def min_weight(edges: DataFrame, least: float) -> DataFrame:
    return edges.filter(F.col("weight") >= least)


def validate(edges: DataFrame) -> DataFrame:
    """One row with the number of edges that break each rule: null ids, weight not above 0 or not finite, duplicates, one direction only."""
    w = F.col("weight")
    each = edges.agg(
        F.count("*").alias("edges"),
        F.count_if(F.col("src").isNull() | F.col("dst").isNull()).alias("null_ids"),
        F.count_if(w.isNull() | ~(w > 0) | F.isnan(w) | (w == float("inf"))).alias("bad_weights"),
        F.count_if(F.col("src") == F.col("dst")).alias("self_loops"),
    )
    pairs = edges.groupBy(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).agg(F.count_if(F.col("src") <= F.col("dst")).alias("f"), F.count_if(F.col("src") > F.col("dst")).alias("r"))
    other = pairs.agg(F.count_if((F.col("f") > 1) | (F.col("r") > 1)).alias("duplicated_pairs"), F.count_if((F.col("a") != F.col("b")) & (F.col("f") != F.col("r"))).alias("one_way_pairs"))
    return each.join(other, how="cross")  # one row each


def nodes_of(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("node")).distinct()


def degrees(edges: DataFrame) -> DataFrame:
    return edges.groupBy(F.col("src").alias("node")).agg(F.count("*").alias("degree"), F.sum("weight").alias("strength"))


def transition(edges: DataFrame, weighted: bool = True) -> DataFrame:
    """Row-normalised weights; nodes without edges have no row."""
    e = edges if weighted else edges.withColumn("weight", F.lit(1.0))
    return e.withColumn("p", F.col("weight") / F.sum("weight").over(Window.partitionBy("src"))).select("src", "dst", "p")


def symmetric_transition(edges: DataFrame) -> DataFrame:
    """Weights over the roots of both strengths: symmetric, with norm 1, on every graph."""
    s = degrees(edges)
    e = edges.join(s.select(F.col("node").alias("src"), F.col("strength").alias("s1")), "src").join(s.select(F.col("node").alias("dst"), F.col("strength").alias("s2")), "dst")
    return e.select("src", "dst", (F.col("weight") / F.sqrt(F.col("s1") * F.col("s2"))).alias("p"))


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, component), the smallest node of each component, by alternating stars."""
    e = settle(edges.selectExpr("greatest(src, dst) AS u", "least(src, dst) AS v").filter("u <> v").distinct(), "stars")
    mark = e.agg(F.count("*"), F.expr("bit_xor(xxhash64(u, v))")).first()
    for _ in range(max_rounds):
        both = e.unionByName(e.selectExpr("v AS u", "u AS v"))
        # the least are written before each join, so that both sides come by an exchange and a hub's side can be split
        least = settle(both.groupBy("u").agg(F.min("v").alias("m")).selectExpr("u", "least(u, m) AS m"), "least")
        large = settle(both.join(least, "u").filter("v > u").selectExpr("v AS u", "m AS v").distinct(), "large-stars")
        least = settle(large.groupBy("u").agg(F.min("v").alias("m")), "least")
        small = large.join(least, "u").selectExpr("v AS u", "m AS v").filter("u <> v").unionByName(least.selectExpr("u", "m AS v"))
        e = settle(small.distinct(), "stars")
        now = e.agg(F.count("*"), F.expr("bit_xor(xxhash64(u, v))")).first()
        if now == mark:
            break
        mark = now
    roots = e.selectExpr("u AS node", "v AS component").unionByName(e.selectExpr("v AS node", "v AS component")).distinct()
    return nodes_of(edges).join(roots, "node", "left").select("node", F.coalesce("component", "node").alias("component"))


def largest_component(edges: DataFrame) -> DataFrame:
    c = connected_components(edges)
    big = c.groupBy("component").count().orderBy(F.desc("count"), "component").limit(1)
    return edges.join(c.join(big, "component").select(F.col("node").alias("src")), "src", "left_semi")


def is_connected(edges: DataFrame) -> bool:
    return connected_components(edges).select("component").distinct().limit(2).count() <= 1


def spanning_forest(edges: DataFrame, seed: int = 7, max_rounds: int = 40) -> DataFrame:
    """One row (src < dst) for each edge of a random spanning forest: every component takes its edge of least draw, components
    merge along them, and so on. The draws order all edges alike, so no cycle closes."""
    e = settle(edges.filter("src < dst").select("src", "dst", fast_draw(seed, F.col("src"), F.col("dst")).alias("o")), "forest-edges")
    labels = nodes_of(edges).withColumn("label", F.col("node"))
    forest = None
    for _ in range(max_rounds):
        a, b = labels.select(F.col("node").alias("src"), F.col("label").alias("a")), labels.select(F.col("node").alias("dst"), F.col("label").alias("b"))
        cross = settle(e.join(a, "src").join(b, "dst").filter("a <> b"), "forest-cross")
        if cross.isEmpty():
            break
        ends = cross.select("a", "o", "src", "dst").unionByName(cross.select(F.col("b").alias("a"), "o", "src", "dst"))
        taken = settle(ends.groupBy("a").agg(F.min(F.struct("o", "src", "dst")).alias("x")).select("x.src", "x.dst").distinct(), "forest-taken")
        forest = taken if forest is None else forest.unionByName(taken)
        e = cross.select("src", "dst", "o")
        merged = taken.join(a, "src").join(b, "dst").select(F.col("a").alias("src"), F.col("b").alias("dst"))
        roots = connected_components(merged.unionByName(merged.selectExpr("dst AS src", "src AS dst")))
        labels = settle(labels.join(roots.select(F.col("node").alias("label"), "component"), "label", "left").select("node", F.coalesce("component", "label").alias("label")), "forest-labels")
    return forest if forest is not None else edges.filter("false").select("src", "dst")


def k_core(edges: DataFrame, k: int, max_rounds: int = 100) -> DataFrame:
    """Edges among nodes that keep k neighbours or more when the others are gone."""
    e = edges
    before = e.count()
    for _ in range(max_rounds):
        kept = degrees(e).filter(F.col("degree") >= k)
        e = settle(e.join(kept.select(F.col("node").alias("src")), "src", "left_semi").join(kept.select(F.col("node").alias("dst")), "dst", "left_semi").select("src", "dst", "weight"), "core")
        if (now := e.count()) == before:
            return e
        before = now
    return e


def has_edge(edges: DataFrame, pairs: DataFrame) -> DataFrame:
    """pairs(src, dst, ...) with is_edge 0 or 1."""
    known = edges.select("src", "dst").distinct().withColumn("is_edge", F.lit(1))
    return pairs.join(known, ["src", "dst"], "left").fillna(0, ["is_edge"])


def degree_between(edges: DataFrame, low: int, high: int) -> DataFrame:
    return degrees(edges).filter(F.col("degree").between(low, high)).select("node")
