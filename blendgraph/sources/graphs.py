"""Graphs built from the given tables, as symmetric edges(src, dst, weight)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..checkpoints import settle
from ..graph import mirrored
from .tables import read_table

TOKEN = r"[^\p{L}\p{N}]+"


def tokens(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), TOKEN), lambda t: t != "")


def shared_item_graph(items: DataFrame, least_holders: int, most_holders: int, least_shared: int = 1, beyond: str = "stars", more: DataFrame | None = None) -> DataFrame:
    """items(node, item), distinct -> an edge between nodes that share least_shared items or more, weight the number shared.

    An item held by least_holders to most_holders nodes links all of them. One held by more links them to the least of them
    (beyond 'stars': a representative and its members, so that a host of any size stays connected and costs one edge a
    node) or is no sign of likeness and links none ('none'). more(src, dst, weight) are edges to add.
    """
    held = settle(items.groupBy("item").agg(F.count("*").alias("n"), F.min("node").alias("hub")).filter(F.col("n") >= max(2, least_holders)), "held")
    kept = items.join(held.filter(F.col("n") <= most_holders).select("item"), "item", "left_semi")
    listed = kept.groupBy("item").agg(F.sort_array(F.collect_list("node")).alias("nodes"))
    pairs = listed.select(F.explode(F.expr("flatten(transform(nodes, (a, i) -> transform(slice(nodes, i + 2, size(nodes)), b -> struct(a AS src, b AS dst))))")).alias("p")).select("p.src", "p.dst")
    if beyond == "stars":
        stars = items.join(held.filter(F.col("n") > most_holders).select("item", "hub"), "item").filter("node <> hub")
        pairs = pairs.unionByName(stars.select(F.col("hub").alias("src"), F.col("node").alias("dst")))
    counted = pairs.groupBy("src", "dst").agg(F.count("*").cast("double").alias("weight")).filter(F.col("weight") >= least_shared)
    return mirrored(counted if more is None else counted.unionByName(more))


def shingle_graph(spark: SparkSession, sf_dir: str, least_shared: int = 2, width: int = 3, most_holders: int = 5) -> DataFrame:
    """Documents that share word shingles held by most_holders different texts or fewer.

    Texts of equal words count once: their documents are linked to the first of them, by all their shingles, and only that
    one looks for other texts. So a group of copies of any size is connected, and its shingles are no frequent ones.
    Shingles travel as 128 bits of hash.
    """
    t = read_table(spark, sf_dir, "documents").select(F.col("doc_id").alias("node"), tokens(F.col("text")).alias("t")).filter(F.size("t") >= width)
    shingles = F.expr(f"array_distinct(transform(sequence(1, size(t) - {width - 1}), i -> array_join(slice(t, i, {width}), ' ')))")
    t = t.withColumn("key", F.sha2(F.array_join("t", " "), 256))
    first = settle(t.groupBy("key").agg(F.min("node").alias("rep"), F.count("*").alias("copies")), "texts")
    hashed = F.transform("x", lambda s: F.struct(F.xxhash64(s).alias("a"), F.xxhash64(s, F.lit(1)).alias("b")))
    known = t.select("key", "node", shingles.alias("x")).join(first, "key").select("node", "rep", hashed.alias("x"))
    # written, as three joins read it; and filters on it would be pushed below, where they cut the text anew for each shingle
    known = settle(known, "shingles")
    copies = known.filter("node <> rep").select(F.col("rep").alias("src"), F.col("node").alias("dst"), F.size("x").cast("double").alias("weight")).filter(F.col("weight") >= least_shared)
    items = known.filter("node = rep").select("node", F.explode("x").alias("item"))
    return shared_item_graph(items, 2, most_holders, least_shared, "none", copies)


def line_graph(spark: SparkSession, sf_dir: str, least_chars: int = 10, most_holders: int = 20) -> DataFrame:
    """Documents that share a line; one that more than most_holders share links them to the first."""
    lines = read_table(spark, sf_dir, "documents").select(F.col("doc_id").alias("node"), F.explode(F.array_distinct(F.split("text", "\n"))).alias("item"))
    return shared_item_graph(lines.filter(F.length("item") >= least_chars), 2, most_holders)


def planted_graph(spark: SparkSession, sf_dir: str, reach: int = 120, same: int = 200, other: int = 8) -> DataFrame:
    """Parts a < b <= a + reach, linked by a rule that favours equal p_type: by an equi join on the exploded reach."""
    p = read_table(spark, sf_dir, "part").select(F.col("p_partkey").alias("node"), F.col("p_type").alias("kind"))
    near = p.select(F.col("node").alias("src"), F.col("kind").alias("k1"), F.explode(F.sequence(F.col("node") + 1, F.col("node") + reach)).alias("dst"))
    rule = F.expr("(7919 * src + 104729 * dst) % 1009") < F.when(F.col("k1") == F.col("k2"), same).otherwise(other)
    # the rule with the wider bound first: it needs no join, and leaves a fifth of the candidates
    wide = near.filter(F.expr("(7919 * src + 104729 * dst) % 1009") < max(same, other))
    linked = wide.join(p.select(F.col("node").alias("dst"), F.col("kind").alias("k2")), "dst").filter(rule)
    return mirrored(linked.select("src", "dst", F.lit(1.0).alias("weight")))


def planted_content(spark: SparkSession, sf_dir: str, draws: int = 6, per_class: int = 10, bound_tenths: int = 4) -> DataFrame:
    """content(node, feature, value) of parts: one-hot tokens drawn by hash, bound to the class bound_tenths times in ten.

    Edges and content depend on each other through the class alone.
    """
    p = read_table(spark, sf_dir, "part").select(F.col("p_partkey").alias("node"), F.col("p_type").alias("kind"))
    kinds = p.select("kind").distinct()
    ranks = kinds.join(kinds.withColumnRenamed("kind", "less"), F.col("less") < F.col("kind"), "left").groupBy("kind").agg(F.count("less").alias("rank"))
    d = p.join(F.broadcast(ranks), "kind").withColumn("t", F.explode(F.sequence(F.lit(0), F.lit(draws - 1))))
    h = F.conv(F.substring(F.md5(F.concat_ws("|", "node", "t").cast("binary")), 1, 8), 16, 10).cast("long")
    d = d.withColumn("h", h)
    n_features = per_class * 6
    token = F.when(F.expr("(h div 10) % 10") < bound_tenths, F.col("rank") * per_class + F.col("h") % per_class).otherwise(F.col("h") % n_features)
    return d.select("node", token.cast("int").alias("feature")).distinct().withColumn("value", F.lit(1.0))


def copurchase_graph(spark: SparkSession, sf_dir: str, least_shared: int = 1) -> DataFrame:
    """Parts bought in one order. An order has few lines, so few pairs."""
    items = read_table(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("node"), F.col("l_orderkey").alias("item")).distinct()
    return shared_item_graph(items, 2, 1 << 30, least_shared)


def bipartite_graph(spark: SparkSession, sf_dir: str, offset: int = 1 << 40) -> DataFrame:
    """Customers and the suppliers they ordered from; supplier ids are shifted by offset."""
    o = read_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    l = read_table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    pairs = o.join(l, F.col("o_orderkey") == F.col("l_orderkey")).select(F.col("o_custkey").alias("src"), (F.col("l_suppkey") + offset).alias("dst")).distinct()
    return mirrored(pairs.withColumn("weight", F.lit(1.0)))


def colink_graph(spark: SparkSession, sf_dir: str, least_shared: int = 4, most_holders: int = 1000) -> DataFrame:
    """Pages that share link targets; one that more than most_holders share links them to the first."""
    items = read_table(spark, sf_dir, "pages").select(F.col("page_id").alias("node"), F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1))).alias("item"))
    return shared_item_graph(items, 2, most_holders, least_shared)


def same_host_graph(spark: SparkSession, sf_dir: str, most_holders: int = 1000) -> DataFrame:
    """Pages of one host: a union of cliques, and of stars for hosts of more than most_holders pages."""
    items = read_table(spark, sf_dir, "pages").select(F.col("page_id").alias("node"), F.regexp_extract("url", "://([^/?#]*)", 1).alias("item"))
    return shared_item_graph(items, 2, most_holders)


def user_key_graph(spark: SparkSession, sf_dir: str, offset: int = 1 << 40) -> DataFrame:
    """Users and the keys in their events' properties; key ids are shifted by offset, weight the number of events."""
    e = read_table(spark, sf_dir, "events").select(F.col("user_id").alias("src"), F.get_json_object("props", "$.k").cast("long").alias("k"))
    pairs = e.filter("src IS NOT NULL AND k IS NOT NULL").groupBy("src", (F.col("k") + offset).alias("dst")).agg(F.count("*").cast("double").alias("weight"))
    return mirrored(pairs)
