"""A planted graph as a Spark data source: edges by rule, for tests of streams and of scale, without a file.

spark.dataSource.register(PlantedEdges); spark.read.format("planted_edges").option("nodes", 1000).load()
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

NAMES = ["src", "dst", "weight"]


def planted_edges(first: int, last: int, classes: int, reach: int, same: int, other: int) -> tuple[list[int], list[int]]:
    """Edges a < b <= a + reach of the nodes first <= a < last: a hash of the pair below a bound that favours one class."""
    src, dst = [], []
    for a in range(first, last):
        for b in range(a + 1, a + reach + 1):
            if (7919 * a + 104729 * b) % 1009 < (same if a % classes == b % classes else other):
                src.append(a)
                dst.append(b)
    return src, dst


class Slice(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class _Options:
    def __init__(self, options: dict):
        get = lambda name, default: int(options.get(name, default))
        self.nodes, self.parts, self.rows = get("nodes", 1000), get("parts", 4), get("rowsPerBatch", 100)
        self.rule = get("classes", 6), get("reach", 120), get("same", 200), get("other", 8)


class PlantedReader(DataSourceReader):
    """One task for each run of nodes; edges come in Arrow batches."""

    def __init__(self, options: dict):
        self.o = _Options(options)

    def partitions(self) -> list[InputPartition]:
        cuts = [self.o.nodes * i // self.o.parts for i in range(self.o.parts + 1)]
        return [Slice(a, b) for a, b in zip(cuts, cuts[1:])]

    def read(self, partition: Slice) -> Iterator[pa.RecordBatch]:
        for a in range(partition.first, partition.last, 1000):
            src, dst = planted_edges(a, min(a + 1000, partition.last), *self.o.rule)
            yield pa.RecordBatch.from_arrays([pa.array(src, pa.int64()), pa.array(dst, pa.int64()), pa.array([1.0] * len(src), pa.float64())], NAMES)


class PlantedStream(SimpleDataSourceStreamReader):
    """The same edges as a stream: each batch has the edges of the next rowsPerBatch nodes, until there are none."""

    def __init__(self, options: dict):
        self.o = _Options(options)

    def initialOffset(self) -> dict:
        return {"node": 0}

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        end = min(start["node"] + self.o.rows, self.o.nodes)
        return self.readBetweenOffsets(start, {"node": end}), {"node": end}

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:
        src, dst = planted_edges(start["node"], end["node"], *self.o.rule)
        return iter([(a, b, 1.0) for a, b in zip(src, dst)])


class PlantedEdges(DataSource):
    @classmethod
    def name(cls) -> str:
        return "planted_edges"

    def schema(self) -> str:
        return "src long, dst long, weight double"

    def reader(self, schema) -> DataSourceReader:
        return PlantedReader(self.options)

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:
        return PlantedStream(self.options)
