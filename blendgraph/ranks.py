"""Row numbers and running totals of whole tables, without a task that sees all rows.

Rows are dealt out by ranges of the order and written, so that the ranges stay what they are; each range is numbered by
itself, and one row a range tells what stands before it.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .checkpoints import settle


def ranked(df: DataFrame, order: list[Column | str], sums: dict[str, str] | None = None, rank: str = "rank") -> DataFrame:
    """df with its row number from 1 and, for each of sums (name -> column), the running total up to and with the row."""
    sums = sums or {}
    d = settle(df.repartitionByRange(*order).withColumn("rk_part", F.spark_partition_id()), "ranges")
    each = d.groupBy("rk_part").agg(F.count("*").alias("n"), *[F.sum(c).alias(name) for name, c in sums.items()])
    # one row a range
    before = Window.orderBy("rk_part").rowsBetween(Window.unboundedPreceding, -1)
    starts = each.select("rk_part", *[F.coalesce(F.sum(c).over(before), F.lit(0)).alias(f"rk_{c}") for c in ("n", *sums)])
    own = Window.partitionBy("rk_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    numbered = d.withColumns({"rk_no": F.count("*").over(own), **{f"rk_own_{name}": F.sum(c).over(own) for name, c in sums.items()}})
    out = numbered.join(starts, "rk_part")
    return out.select(*df.columns, (F.col("rk_no") + F.col("rk_n")).alias(rank), *[(F.col(f"rk_own_{name}") + F.col(f"rk_{name}")).alias(name) for name in sums])


def ranked_within(df: DataFrame, group: str, order: list[Column | str], sums: dict[str, str] | None = None, rank: str = "rank") -> DataFrame:
    """As ranked, from 1 in each group. A group of any size is dealt over as many ranges as it fills."""
    sums = sums or {}
    d = settle(ranked(df, [group, *order], sums, rank), "ranked")
    starts = d.groupBy(group).agg(F.min(rank).alias("rk_first"), *[F.min_by(F.col(name) - F.col(c), rank).alias(f"rk_{name}") for name, c in sums.items()])
    out = d.join(settle(starts, "starts").withColumnRenamed(group, "rk_group"), F.col(group).eqNullSafe(F.col("rk_group")))
    return out.select(*df.columns, (F.col(rank) - F.col("rk_first") + 1).alias(rank), *[(F.col(name) - F.col(f"rk_{name}")).alias(name) for name in sums])
