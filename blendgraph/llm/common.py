"""Pieces shared by the training-data operators."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A-Z become a-z, every other byte stays.
LOWER = bytes.maketrans(bytes(range(65, 91)), bytes(range(97, 123)))
#: As LOWER, and every ASCII byte that is no digit or letter becomes a space. The bytes of
#: non-ASCII characters are all above 0x7F and stay, so words are the pieces between spaces.
WORDS = bytes(b if b > 127 or chr(b).isalnum() else 32 for b in range(256)).translate(LOWER)
#: Java and DuckDB pattern of a word between ASCII white space.
SPACED_WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir, or in local mode (tests) one set here where it is unset."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        jsc = spark.sparkContext._jsc.sc()
        if jsc.getCheckpointDir().isEmpty():
            if not spark.sparkContext.master.startswith("local"):
                raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
            spark.sparkContext.setCheckpointDir("/tmp/blendgraph-checkpoints")
        found = jsc.getCheckpointDir().get()
    return found.rstrip("/")


def written(df: DataFrame, name: str) -> DataFrame:
    """Write df to the shared folder and read it again: cuts the lineage, survives lost executors. What is written goes
    when the driver ends, as results read it until then."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/blendgraph/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    delete_at_end(spark, path)
    return spark.read.schema(df.schema).parquet(path)


def delete_at_end(spark: SparkSession, path: str) -> None:
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(where)


def utf8(column: pa.Array) -> list[bytes | None]:
    """The column's texts as bytes; null stays None."""
    return column.cast(pa.large_binary()).to_pylist()


def per_batch(f: Callable[[pa.RecordBatch], pa.RecordBatch]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """f applied to each Arrow batch, in slices of about 8 MB so that long texts do not pile up."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            step = max(1, int(batch.num_rows * 8e6 / max(batch.nbytes, 1)))
            for at in range(0, batch.num_rows, step):
                yield f(batch.slice(at, step))

    return run


def spaced_words(text: Column) -> Column:
    """Number of words between ASCII white space; null has none."""
    return F.coalesce(F.regexp_count(text, F.lit(SPACED_WORD)), F.lit(0)).cast("long")


def draw32(*parts: Column | str | int) -> Column:
    """32 hashed bits of the parts as a long, by md5: the same in every plan and in SQL."""
    cols = [p if isinstance(p, Column) else F.lit(str(p)) for p in parts]
    return F.conv(F.substring(F.md5(F.concat_ws("|", *cols).cast("binary")), 1, 8), 16, 10).cast("long")
