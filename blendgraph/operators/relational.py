"""Band, as-of and salted joins, set operations, rollups, top-k."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def band_join(left: DataFrame, right: DataFrame, key: str, low: int, high: int) -> DataFrame:
    """Rows with left.key + low <= right.key <= left.key + high, as l and r structs.

    Keys fall into buckets as wide as the band; a left row goes to the one or two buckets that its band touches, and buckets
    meet in an equi join, so nothing is compared beyond neighbouring buckets.
    """
    width = max(1, high - low)
    l = left.select(F.struct("*").alias("l")).withColumn("b", F.explode(F.expr(f"array_distinct(array(floor((l.{key} + {low}) / {width}), floor((l.{key} + {high}) / {width})))")))
    r = right.select(F.struct("*").alias("r")).withColumn("b", F.expr(f"floor(r.{key} / {width})"))
    return l.join(r, "b").filter(F.expr(f"r.{key} BETWEEN l.{key} + {low} AND l.{key} + {high}")).select("l", "r")


def next_event(events: DataFrame, within_seconds: int = 1800) -> DataFrame:
    """Each event with the same user's next one and the seconds between, null if farther than within_seconds."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    seconds = (F.unix_micros(F.lead("ts").over(w).cast("timestamp")) - F.unix_micros(F.col("ts").cast("timestamp"))) / 1e6
    d = events.withColumns({"next_id": F.lead("event_id").over(w), "gap": seconds})
    near = F.col("gap") <= within_seconds
    return d.select("event_id", "user_id", F.when(near, F.col("next_id")).alias("next_id"), F.when(near, F.col("gap")).alias("gap"))


def salted_join(large: DataFrame, small: DataFrame, key: str, salts: int = 16) -> DataFrame:
    """An inner join whose hot keys go to salts tasks each: large rows get a salt by hash, small rows every salt. The small
    side is never sent out: its size is estimated without the salts."""
    l = large.withColumn("_salt", F.pmod(F.xxhash64(*large.columns), F.lit(salts)).cast("int"))
    s = small.withColumn("_salt", F.explode(F.expr(f"sequence(0, {salts - 1})")))
    return l.join(s.hint("merge"), [key, "_salt"]).drop("_salt")


def co_bucketed_join(left: DataFrame, right: DataFrame, key: str, name: str, buckets: int = 8) -> DataFrame:
    """Both sides as tables bucketed and sorted by key: joins of them need no exchange, however often they are made."""
    spark = left.sparkSession
    for side, d in (("l", left), ("r", right)):
        spark.sql(f"DROP TABLE IF EXISTS {name}_{side}")
        d.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(f"{name}_{side}")
    return spark.table(f"{name}_l").join(spark.table(f"{name}_r"), key)


def exact_pairs(nodes: DataFrame, limit: int = 3000) -> DataFrame:
    """All ordered pairs of a small node set; refused above limit, which bounds the rows."""
    if nodes.count() > limit:
        raise ValueError(f"over {limit} nodes")
    return nodes.select(F.col("node").alias("src")).join(F.broadcast(nodes.select(F.col("node").alias("dst"))), F.col("src") != F.col("dst"))


def edges_between(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """Edges with both ends in nodes: two semi joins."""
    return edges.join(nodes.select(F.col("node").alias("src")), "src", "left_semi").join(nodes.select(F.col("node").alias("dst")), "dst", "left_semi").select("src", "dst", "weight")


def set_operations(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: rows in a and b, in either, in a alone, by (src, dst)."""
    x, y = a.select("src", "dst"), b.select("src", "dst")
    counts = [d.agg(F.count("*").alias(n)) for d, n in ((x.intersect(y), "both"), (x.union(y).distinct(), "either"), (x.exceptAll(y), "first_only"))]
    return counts[0].join(counts[1], how="cross").join(counts[2], how="cross")  # one row each


def grouped_accuracy(pred: DataFrame, keys: list[str], how: str = "rollup") -> DataFrame:
    """Accuracy by keys and their totals: rollup, cube, or grouping sets of each key alone and all rows."""
    hit = (F.col("label") == F.col("predicted")).cast("double")
    aggs = (F.avg(hit).alias("accuracy"), F.count("*").alias("n"))
    if how == "rollup":
        return pred.rollup(*keys).agg(*aggs)
    if how == "cube":
        return pred.cube(*keys).agg(*aggs)
    return pred.groupingSets([[F.col(k)] for k in keys] + [[]], *[F.col(k) for k in keys]).agg(*aggs)


def top_links(scores: DataFrame, k: int) -> DataFrame:
    """The k best pairs: each task keeps its own k first."""
    return scores.orderBy(F.desc("score"), "src", "dst").limit(k)
