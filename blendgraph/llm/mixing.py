"""Mixing sources to target weights by systematic sampling."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import draw32, spaced_words

#: Hash cells of documents of like size; a source's documents spread over them.
SPREAD = 64


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = (5, 2, 1), share: float = 1.5, cap: float = 2.0) -> DataFrame:
    """sizes(mx_source, mx_source_size) -> the same, mx_target and mx_rate (copies of each document).

    Sources by code point, null last, take the weights in turn. A target that would be above cap times its
    source's size stays there and the rest is shared among the others by weight: with the sources ordered by
    size over weight, the capped ones come first, so one pass of running sums finds the common level.
    One row a source stands in this window, never documents.
    """
    alone = Window.partitionBy(F.lit(0))
    ranked = sizes.withColumn("mx_rank", F.row_number().over(alone.orderBy(F.col("mx_source").asc_nulls_last())) - 1)
    weight = F.element_at(F.array(*map(F.lit, weights)), (F.col("mx_rank") % len(weights) + 1).cast("int")).cast("double")
    ranked = ranked.withColumns({"mx_weight": weight, "mx_cap": F.col("mx_source_size") * F.lit(cap), "mx_total": F.sum("mx_source_size").over(alone) * F.lit(share)})
    by_level = alone.orderBy(F.col("mx_cap") / F.col("mx_weight"), "mx_rank")
    capped = F.coalesce(F.sum("mx_cap").over(by_level.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    left = F.sum("mx_weight").over(by_level.rowsBetween(0, Window.unboundedFollowing))
    level = ranked.withColumn("mx_level", (F.col("mx_total") - capped) / left)
    level = level.withColumn("mx_level", F.max(F.when(F.col("mx_level") * F.col("mx_weight") <= F.col("mx_cap"), F.col("mx_level"))).over(alone))
    target = F.coalesce(F.least(F.col("mx_level") * F.col("mx_weight"), F.col("mx_cap")), F.col("mx_cap"))
    return level.select("mx_source", "mx_source_size", target.alias("mx_target"), F.when(F.col("mx_source_size") > 0, target / F.col("mx_source_size")).otherwise(0.0).alias("mx_rate"))


def plan_mixture(docs: DataFrame, weights: tuple[int, ...] = (5, 2, 1), share: float = 1.5, cap: float = 2.0, seed: int = 17, size: Column | None = None) -> DataFrame:
    """Add mx_size, mx_source_size, mx_target and mx_copies to docs(doc_id, text, source, ...).

    Every document of a source has the same expected number of copies, its source's rate. They are summed along
    an order of like sizes, and a document is emitted once for each integer that the running sum, shifted by one
    random offset of the source, passes at it. Neighbours have like sizes, so the words taken stay near the target.

    The order has cells (size class, hash), of which the counts, at most some thousands a source, are summed
    first; only positions within a cell need a window over documents. So no task holds a whole source, and
    SPREAD splits a source whose documents all have one size.

    Null or empty text: size 0, still counted as a position. Null source: a source of its own. Repeated rows:
    each its own document. Empty table: no rows. Columns whose names start with mx_ are dropped.
    """
    docs = docs.drop(*[c for c in docs.columns if c.startswith("mx_")])
    n = spaced_words(F.col("text")) if size is None else size
    d = docs.withColumn("mx_size", n).withColumn("mx_source", F.col("source"))
    bits = F.length(F.bin("mx_size"))
    # bit length and the next three bits: sizes in a class differ by an eighth at most
    d = d.withColumns({"mx_class": (bits * 16 + F.expr("shiftright(mx_size, greatest(length(bin(mx_size)) - 4, 0))")).cast("int"), "mx_hash": F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary"))})
    d = d.withColumn("mx_cell", F.conv(F.substring("mx_hash", 1, 2), 16, 10).cast("int") % SPREAD)
    cell = ["mx_source", "mx_class", "mx_cell"]
    counts = d.groupBy(*cell).agg(F.count("*").alias("mx_n"), F.sum("mx_size").alias("mx_sum"))
    targets = source_targets(counts.groupBy("mx_source").agg(F.sum("mx_sum").alias("mx_source_size")), weights, share, cap)
    before = Window.partitionBy("mx_source").orderBy("mx_class", "mx_cell").rowsBetween(Window.unboundedPreceding, -1)
    cells = counts.select(*cell, F.coalesce(F.sum("mx_n").over(before), F.lit(0)).alias("mx_before"))
    cells = cells.alias("c").join(targets.alias("t"), F.expr("c.mx_source <=> t.mx_source")).select("c.*", "mx_source_size", "mx_target", "mx_rate")
    d = d.withColumn("mx_row", F.row_number().over(Window.partitionBy(*cell).orderBy("mx_size", "mx_hash", "doc_id")))
    joined = d.alias("d").join(cells.alias("c"), F.expr("d.mx_source <=> c.mx_source AND d.mx_class = c.mx_class AND d.mx_cell = c.mx_cell"))
    offset = draw32(F.coalesce(F.col("d.mx_source"), F.lit("")), seed) / F.lit(4294967296.0)
    at = F.col("mx_before") + F.col("mx_row")
    copies = F.floor(offset + F.col("mx_rate") * at) - F.floor(offset + F.col("mx_rate") * (at - 1))
    keep = [F.col(f"d.`{c}`") for c in docs.columns]
    return joined.select(*keep, F.col("d.mx_size"), F.col("mx_source_size"), F.col("mx_target"), copies.cast("long").alias("mx_copies"))


def mix(docs: DataFrame, **options) -> DataFrame:
    """The mixed documents: each row of docs as often as its copies, with mx_copy counting from 1.

    Nulls, empty and repeated rows and reserved names as in plan_mixture; rows without words may be taken, and count
    nothing. An empty table gives an empty one."""
    docs = docs.drop(*[c for c in docs.columns if c.startswith("mx_")])
    planned = plan_mixture(docs, **options).filter("mx_copies > 0")
    out = planned.withColumn("mx_copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("mx_copies"))))
    return out.select(*docs.columns, "mx_copy")
