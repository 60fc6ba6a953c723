"""Link scores from neighbourhoods. pairs(src, dst, ...) keep their columns and get score."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .graph import degrees


def _shared(edges: DataFrame, pairs: DataFrame) -> DataFrame:
    """(src, dst, mid): the common neighbours of the pairs alone. The neighbours of each pair's first node are looked up and
    kept where the second has them, so no wedge that no pair asks for is made."""
    e = edges.select("src", "dst").distinct()
    first = pairs.select("src", "dst").distinct().join(e.select("src", F.col("dst").alias("mid")), "src")
    return first.join(e.select(F.col("src").alias("dst"), F.col("dst").alias("mid")), ["dst", "mid"], "left_semi")


def _scored(pairs: DataFrame, scores: DataFrame) -> DataFrame:
    return pairs.join(scores, ["src", "dst"], "left").fillna(0.0, ["score"])


def _degrees(edges: DataFrame, pairs: DataFrame, isolated: bool) -> DataFrame:
    """pairs with the degrees of both ends; isolated: whether pairs of which an end has no edge stay, with 0."""
    d, how = degrees(edges).select("node", "degree"), "left" if isolated else "inner"
    out = pairs.join(d.select(F.col("node").alias("src"), F.col("degree").alias("d1")), "src", how).join(d.select(F.col("node").alias("dst"), F.col("degree").alias("d2")), "dst", how)
    return out.fillna(0, ["d1", "d2"])


def common_neighbors(edges: DataFrame, pairs: DataFrame) -> DataFrame:
    return _scored(pairs, _shared(edges, pairs).groupBy("src", "dst").agg(F.count("*").cast("double").alias("score")))


def jaccard(edges: DataFrame, pairs: DataFrame, isolated: bool = True) -> DataFrame:
    """0 if neither has a neighbour."""
    d = _degrees(edges, common_neighbors(edges, pairs).withColumnRenamed("score", "c"), isolated)
    union = F.col("d1") + F.col("d2") - F.col("c")
    return d.withColumn("score", F.when(union > 0, F.col("c") / union).otherwise(0.0)).select(*pairs.columns, "score")


def adamic_adar(edges: DataFrame, pairs: DataFrame) -> DataFrame:
    # a common neighbour of two nodes has two neighbours or more
    d = degrees(edges).filter("degree > 1").select(F.col("node").alias("mid"), (1 / F.log(F.col("degree").cast("double"))).alias("w"))
    return _scored(pairs, _shared(edges, pairs).join(d, "mid").groupBy("src", "dst").agg(F.sum("w").alias("score")))


def preferential_attachment(edges: DataFrame, pairs: DataFrame, isolated: bool = True) -> DataFrame:
    d = _degrees(edges, pairs, isolated)
    return d.withColumn("score", (F.col("d1") * F.col("d2")).cast("double")).select(*pairs.columns, "score")


def content_cosine(content: DataFrame, pairs: DataFrame) -> DataFrame:
    """Cosine of the raw content: what content alone says about a pair. No side is sent out: content that is made by exploding
    rows is estimated as if it had a row a node."""
    lengths = content.groupBy("node").agg(F.sqrt(F.sum(F.col("value") * F.col("value"))).alias("l"))
    scaled = content.join(lengths.hint("merge"), "node").select("node", "feature", (F.col("value") / F.col("l")).alias("x"))
    a = scaled.withColumnRenamed("node", "src").hint("merge")
    b = scaled.select(F.col("node").alias("dst"), "feature", F.col("x").alias("y")).hint("merge")
    dots = pairs.select("src", "dst").distinct().join(a, "src").join(b, ["dst", "feature"]).groupBy("src", "dst").agg(F.sum(F.col("x") * F.col("y")).alias("score"))
    return _scored(pairs, dots)


def hash_score(pairs: DataFrame, seed: int = 1) -> DataFrame:
    """Chance level."""
    from .randomness import unit

    return pairs.withColumn("score", unit(F.lit(seed), F.col("src"), F.col("dst")))
