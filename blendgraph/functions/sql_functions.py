"""register_functions(spark) makes sigmoid, softplus, cosine_sim, vec_dot, hash_u and pairs_in_window known to SQL."""

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import arrow_udf, udtf

EXPRESSIONS = {
    "sigmoid(x DOUBLE) RETURNS DOUBLE": "1 / (1 + exp(-x))",
    "softplus(x DOUBLE) RETURNS DOUBLE": "greatest(x, 0D) + log1p(exp(-abs(x)))",
    "vec_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
    "vec_length(a ARRAY<DOUBLE>) RETURNS DOUBLE": "sqrt(aggregate(a, 0D, (s, x) -> s + x * x))",
    "cosine_sim(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "coalesce(try_divide(aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x), sqrt(aggregate(a, 0D, (s, x) -> s + x * x)) * sqrt(aggregate(b, 0D, (s, x) -> s + x * x))), 0D)",
    "hash_u(key STRING) RETURNS DOUBLE": "CAST(conv(substr(md5(key), 1, 8), 16, 10) AS BIGINT) / 4294967296D",
}


def _matrix(column: pa.Array) -> np.ndarray:
    return np.array(column.to_pylist(), float)


@arrow_udf(T.DoubleType())
def arrow_dot(a: pa.Array, b: pa.Array) -> pa.Array:
    return pa.array(np.einsum("ij,ij->i", _matrix(a), _matrix(b)))


@arrow_udf(T.DoubleType())
def arrow_cosine(a: pa.Array, b: pa.Array) -> pa.Array:
    x, y = _matrix(a), _matrix(b)
    length = np.linalg.norm(x, axis=1) * np.linalg.norm(y, axis=1)
    return pa.array(np.where(length > 0, np.einsum("ij,ij->i", x, y) / np.where(length > 0, length, 1), 0.0))


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def arrow_vec_sum(v: pd.Series) -> list:
    """The sum of a group's arrays, in one place: for small groups. factorize.vec_sum sums on each task first."""
    return np.stack(v.to_list()).sum(axis=0).tolist() if len(v) else []


@udtf(returnType=T.StructType([T.StructField("node", T.LongType()), T.StructField("context", T.LongType()), T.StructField("gap", T.IntegerType())]))
class PairsInWindow:
    """pairs_in_window(path, window): the ordered pairs of a path at most window places apart."""

    def eval(self, path: list, window: int):
        for i, node in enumerate(path):
            for gap in range(1, min(window, len(path) - 1 - i) + 1):
                yield node, path[i + gap], gap


@udtf(returnType=T.StructType([T.StructField("position", T.IntegerType()), T.StructField("node", T.LongType())]))
class WalkFrom:
    """walk_from(start, neighbours by node as a map of arrays, length, seed): one walk over a small graph."""

    def eval(self, start: int, neighbours: dict, length: int, seed: int):
        r = np.random.default_rng([seed, start & 0xFFFFFFFF])
        node = start
        yield 0, node
        for at in range(1, length):
            options = (neighbours or {}).get(node)
            if not options:
                return
            node = options[int(r.integers(len(options)))]
            yield at, node


def register_functions(spark: SparkSession) -> list[str]:
    """Register all; -> their names."""
    for head, body in EXPRESSIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    spark.udtf.register("pairs_in_window", PairsInWindow)
    spark.udtf.register("walk_from", WalkFrom)
    spark.udf.register("arrow_cosine", arrow_cosine)
    spark.udf.register("arrow_dot", arrow_dot)
    return [h.split("(")[0] for h in EXPRESSIONS] + ["pairs_in_window", "walk_from", "arrow_cosine", "arrow_dot"]
