"""Reading tables and edge lists; writing results."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

EDGES = T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType()), T.StructField("weight", T.DoubleType())])


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", **options: str) -> DataFrame:
    """An edge list in parquet, orc, csv or json files, or a catalog table (fmt 'table')."""
    if fmt == "table":
        return spark.table(path).select(*[F.col(f.name).cast(f.dataType) for f in EDGES.fields])
    if fmt not in ("parquet", "orc", "csv", "json"):
        raise ValueError(f"no such format: {fmt}")
    return spark.read.format(fmt).schema(EDGES).options(**options).load(path)


def write_vectors(vectors: DataFrame, path: str, blocks: int = 64, key: str = "node") -> None:
    """Vectors as Parquet, dealt out and sorted by key, so that readers join without a sort of their own."""
    vectors.repartition(blocks, key).sortWithinPartitions(key).write.mode("overwrite").parquet(path)


def write_cooc(cooc: DataFrame, path: str, blocks: int = 64) -> None:
    """Counts as Parquet, a folder for each block of nodes: readers of some nodes read some folders."""
    cooc.withColumn("block", F.pmod(F.xxhash64("node"), F.lit(blocks)).cast("int")).repartition("block").write.mode("overwrite").partitionBy("block").parquet(path)


def write_word2vec_text(vectors: DataFrame, path: str, key: str = "node", value: str = "w") -> None:
    """Lines of a key and its numbers, as word vector tools read them."""
    vectors.select(F.concat_ws(" ", F.col(key).cast("string"), F.concat_ws(" ", F.transform(value, lambda x: x.cast("string"))))).write.mode("overwrite").text(path)


def write_model_card(spark: SparkSession, path: str, card: dict) -> None:
    spark.createDataFrame([(json.dumps(card, sort_keys=True),)], "value string").coalesce(1).write.mode("overwrite").text(path)
