"""Cutting lineage in the folder that all executors share."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session; in local mode, as in tests, one is set here where it is unset."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        jsc = spark.sparkContext._jsc.sc()
        if jsc.getCheckpointDir().isEmpty():
            if not spark.sparkContext.master.startswith("local"):
                raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
            spark.sparkContext.setCheckpointDir("/tmp/blendgraph-checkpoints")
        found = jsc.getCheckpointDir().get()
    return found.rstrip("/")


def settle(df: DataFrame, name: str = "step") -> DataFrame:
    """Write df as Parquet to the shared folder and read it back: short plans in loops, and no loss with an executor. What
    is written goes when the driver ends, as results read it until then."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/blendgraph/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(where)
    out = spark.read.schema(df.schema).parquet(path)
    out._settled = True
    return out


def settled(df: DataFrame, columns: list[str], name: str = "step") -> DataFrame:
    """df's columns, written unless settle has written df, so that nothing is there twice."""
    if not getattr(df, "_settled", False):
        return settle(df.select(*columns), name)
    out = df.select(*columns)
    out._settled = True
    return out
