"""A transition as lists in each worker process, for products with it that need no shuffle."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .checkpoints import settle

#: Largest transition, in MB, that is gathered and sent to each worker process; beyond, joins do the work.
LINKS_MB = 256.0
#: Entries that a product writes out at once: all of them would be several times the lists.
BLOCK = 1 << 21
#: Most values that are told apart by numbers.
MOST_VALUES = 1 << 16


@dataclass
class Links:
    """Node ids in order and, of each, where its entries start, whom they lead to (as places of ids) and their values: as
    numbers of the values that there are, where these are few."""

    ids: np.ndarray
    start: np.ndarray
    at: np.ndarray
    p: np.ndarray
    values: np.ndarray | None = None

    @property
    def rows(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.ids), dtype=np.int32), np.diff(self.start))

    def entries(self) -> np.ndarray:
        return self.p if self.values is None else self.values[self.p]

    def times(self, x: np.ndarray, rows: np.ndarray) -> np.ndarray:
        """The transition times one column x."""
        out = np.zeros(len(self.ids))
        for a in range(0, len(self.at), BLOCK):
            own = rows[a : a + BLOCK]
            # entries are in the order of their rows
            out[own[0] : own[-1] + 1] += np.bincount(own - own[0], self._part(a) * x[self.at[a : a + BLOCK]])
        return out

    def back(self, y: np.ndarray, rows: np.ndarray) -> np.ndarray:
        """The transposed transition times one column y."""
        out = np.zeros(len(self.ids))
        for a in range(0, len(self.at), BLOCK):
            out += np.bincount(self.at[a : a + BLOCK], self._part(a) * y[rows[a : a + BLOCK]], len(self.ids))
        return out

    def _part(self, a: int) -> np.ndarray:
        p = self.p[a : a + BLOCK]
        return p if self.values is None else self.values[p]


def gather_links(t: DataFrame, limit_mb: float = LINKS_MB) -> Links | None:
    """t(src, dst, p) as lists on the driver, or None if they are over limit_mb."""
    t = t.select("src", "dst", "p")
    names = settle(t.select(F.col("src").alias("node")).union(t.select("dst")).distinct(), "names")
    n, entries = names.count(), t.count()
    if (12 * entries + 16 * n) / 1e6 > limit_mb:
        return None
    ids = names.orderBy("node").toArrow().column(0).to_numpy()
    sent = t.sparkSession.sparkContext.broadcast(ids)

    def placed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ends = np.concatenate([[0], np.cumsum(batch.column(1).value_lengths().to_numpy(zero_copy_only=False))]).astype(np.int32)
            at = np.searchsorted(sent.value, batch.column(1).flatten().to_numpy(zero_copy_only=False)).astype(np.int32)
            own = np.searchsorted(sent.value, batch.column(0).to_numpy(zero_copy_only=False)).astype(np.int32)
            yield pa.RecordBatch.from_arrays([pa.array(own), pa.ListArray.from_arrays(pa.array(ends), pa.array(at)), pa.ListArray.from_arrays(pa.array(ends), batch.column(2).flatten())], ["i", "at", "p"])

    listed = t.groupBy("src").agg(F.sort_array(F.collect_list(F.struct("dst", F.col("p").cast("double").alias("p")))).alias("l")).select("src", F.col("l.dst").alias("dst"), F.col("l.p").alias("p"))
    found, slices = settle(listed.mapInArrow(placed, "i int, at array<int>, p array<double>"), "links"), max(1, entries // 2_000_000)
    sizes = np.zeros(n, np.int64)
    t = found.select("i", F.size("at").alias("many")).toArrow()
    sizes[t.column(0).to_numpy()] = t.column(1).to_numpy()
    # values as numbers at once, where they are few: the driver holds no column of them all
    values = np.sort(found.select(F.explode("p").alias("p")).distinct().limit(MOST_VALUES + 1).toArrow().column(0).to_numpy())
    few = len(values) <= MOST_VALUES
    start, at = np.concatenate([[0], np.cumsum(sizes)]), np.empty(entries, np.int32)
    p = np.empty(entries, np.min_scalar_type(max(len(values) - 1, 0)) if few else float)
    # a slice at a time, so that the driver never has them twice
    for k in range(slices):
        for batch in found.filter(f"i % {slices} = {k}").toArrow().to_batches():
            own = batch.column(0).to_numpy()
            to = ranges(start[own], sizes[own])
            of = batch.column(2).flatten().to_numpy()
            at[to], p[to] = batch.column(1).flatten().to_numpy(), np.searchsorted(values, of) if few else of
    sent.destroy()
    return Links(ids, start, at, p, values if few else None)


def ranges(first: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """first, first + 1, ... as many as sizes says, one after another."""
    return np.repeat(first - np.concatenate([[0], np.cumsum(sizes)[:-1]]), sizes) + np.arange(int(sizes.sum()))
