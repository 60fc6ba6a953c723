"""A training corpus from documents: clean, drop repeated lines, near copies and test items, then mix the sources."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blendgraph.llm import decontamination, line_chunks, line_quality, mixing, simhash
from blendgraph.llm.common import delete_at_end, shared_folder, table


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Failing lines go; documents that lose too much, and those that fail the base rules, go."""
    return line_quality.clean_documents(docs)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Chunks and other runs of lines that stand elsewhere before go; documents of which nothing is left go. n_chars, if
    there, is counted anew."""
    d = line_chunks.drop_repeated_chunks(docs, runs=True)
    d = d.filter(F.expr("lc_removed_lines = 0 OR length(trim(text)) > 0"))
    if "n_chars" in docs.columns:
        d = d.withColumn("n_chars", F.when(F.col("lc_removed_lines") > 0, F.length("text")).otherwise(F.col("n_chars")).cast(docs.schema["n_chars"].dataType))
    return d.select(*docs.columns)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays, the one with the smallest doc_id: five-word shingles of a
    similarity of 0.8 or more, by SimHash blocks and the Hamming check."""
    return simhash.keep_one_each(docs, width=5)


def test_items(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold ten words in a row of a benchmark item go."""
    return decontamination.drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources at their weights; a document that is taken more than once stands there as often, with mx_copy from 1."""
    return mixing.mix(docs)


STAGES = [("quality rules", quality), ("line dedup", lines), ("SimHash near-dedup", near_copies), ("benchmark decontamination", test_items), ("source mixing", mixture)]

#: Regular expressions over single lines, XXH64 fingerprints and components are beyond SQL; tests hold it against plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages one after another over documents, each written as Parquet to the shared folder and read again."""
    folder = f"{shared_folder(spark)}/blendgraph/corpus-{uuid.uuid4().hex}"
    docs = table(spark, sf_dir, "documents")
    for number, (_, stage) in enumerate(STAGES[:-1]):
        out = stage(spark, docs, sf_dir)
        out.write.parquet(f"{folder}/{number}")
        delete_at_end(spark, f"{folder}/{number}")
        docs = spark.read.schema(out.schema).parquet(f"{folder}/{number}")
    return STAGES[-1][1](spark, docs, sf_dir)
