"""Sums over all contexts as functions of a node's vector, for exact negatives where nodes times contexts are too many.

With vectors of few numbers, sum(total · softplus(h · w)) and sum(total · h · sigmoid(h · w)) over the contexts are smooth in w:
their values at the Chebyshev points of a box around all w give them everywhere in it. No context and no pair is left out;
the degree is set so that what the interpolation misses is about TOLERANCE of the sum or less.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession

TOLERANCE = 1e-11
MOST_POINTS = 24


def degree_for(h: np.ndarray, totals: np.ndarray, half: np.ndarray) -> int | None:
    """Points a dimension: softplus and sigmoid are analytic up to distance pi of the real line, so a context's part of the error
    falls by rho a point, rho the sum of the half axes of the ellipse that its h leaves. None: more than MOST_POINTS."""
    share = totals / max(totals.sum(), 1e-300)
    z = np.pi / np.maximum(np.abs(h) * half[None, :], 1e-12)
    log_rho = np.log(z + np.sqrt(1 + z * z))
    for m in range(4, MOST_POINTS + 1):
        if float((share[:, None] * np.exp(-m * log_rho)).sum()) < TOLERANCE:
            return m
    return None


class Grid:
    """Chebyshev points of a box, m in each dimension."""

    def __init__(self, low: np.ndarray, high: np.ndarray, m: int):
        self.middle, self.half, self.m = (low + high) / 2, np.maximum((high - low) / 2, 1e-9), m
        self.at = np.cos(np.pi * (np.arange(m) + 0.5) / m)
        self.scale = (-1.0) ** np.arange(m) * np.sin(np.pi * (np.arange(m) + 0.5) / m)

    @property
    def size(self) -> int:
        return self.m ** len(self.half)

    def points(self, first: int, last: int) -> np.ndarray:
        places = np.unravel_index(np.arange(first, last), (self.m,) * len(self.half))
        return np.stack([self.middle[k] + self.half[k] * self.at[p] for k, p in enumerate(places)], axis=1)

    def weights(self, w: np.ndarray) -> list[np.ndarray]:
        """Of each dimension: how much each point counts at each w (barycentric)."""
        out = []
        for k in range(w.shape[1]):
            far = (w[:, k, None] - self.middle[k]) / self.half[k] - self.at[None, :]
            hit = far == 0
            part = self.scale[None, :] / np.where(hit, 1.0, far)
            part = np.where(hit.any(axis=1)[:, None], hit.astype(float), part)
            out.append(part / part.sum(axis=1, keepdims=True))
        return out

    def read(self, table: np.ndarray, w: np.ndarray, rows: int = 256) -> np.ndarray:
        """table(point, column) at each w."""
        out = np.empty((len(w), table.shape[1]))
        for a in range(0, len(w), rows):
            b = self.weights(w[a : a + rows])
            v = (b[0] @ table.reshape(self.m, -1)).reshape(len(b[0]), -1)
            for x in b[1:]:
                v = np.matmul(x[:, None, :], v.reshape(len(x), self.m, -1))[:, 0, :]
            out[a : a + rows] = v
        return out

    def spread(self, w: np.ndarray, values: np.ndarray, rows: int = 4096) -> np.ndarray:
        """The transpose of read: (point, column) sums of values(w, column)."""
        out = np.zeros((self.size, values.shape[1]))
        cut = (w.shape[1] + 1) // 2
        for a in range(0, len(w), rows):
            b = self.weights(w[a : a + rows])
            left, right = (_outer(x, len(b[0])) for x in (b[:cut], b[cut:]))
            for c in range(values.shape[1]):
                out[:, c] += (left.T @ (right * values[a : a + rows, c, None])).ravel()
        return out


def _outer(parts: list[np.ndarray], n: int) -> np.ndarray:
    out = np.ones((n, 1))
    for p in parts:
        out = (out[:, :, None] * p[:, None, :]).reshape(n, -1)
    return out


def pair_table(points: np.ndarray, others: np.ndarray, share: np.ndarray, block: int = 2048) -> np.ndarray:
    """(point, 1 + dim): share · softplus and share · other · sigmoid over all others."""
    out = np.zeros((len(points), 1 + points.shape[1]))
    for a in range(0, len(others), block):
        h, t = others[a : a + block], share[a : a + block]
        x = points @ h.T
        tail = np.exp(-np.abs(x))
        out[:, 0] += (np.maximum(x, 0) + np.log(1 + tail)) @ t
        out[:, 1:] += np.where(x >= 0, 1 / (1 + tail), tail / (1 + tail)) @ (h * t[:, None])
    return out


def context_sums(spark: SparkSession, h: np.ndarray, totals: np.ndarray, low: np.ndarray, high: np.ndarray, slices: int = 48) -> tuple[Grid, np.ndarray] | None:
    """A grid of the box low..high of node vectors, and at its points the sums of total · softplus and of total · h · sigmoid over
    all contexts. Both are smooth in h as well, so each context is first spread over the points of a grid of its own side;
    then grid meets grid. Work is linear in the contexts. None where vectors are so long that it takes too many points."""
    m = degree_for(h, totals, np.maximum((high - low) / 2, 1e-9))
    if m is None:
        return None
    nodes = Grid(low, high, m)
    every, own = nodes.points(0, nodes.size), (h.min(axis=0), h.max(axis=0))
    m = degree_for(every, np.ones(len(every)), np.maximum((own[1] - own[0]) / 2, 1e-9))
    if m is None:
        return None
    contexts = Grid(*own, m)
    cuts = [len(h) * i // slices for i in range(slices + 1)]
    share = sum(_sliced(spark, (contexts, h, totals, cuts), lambda x, i: x[0].spread(x[1][x[3][i] : x[3][i + 1]], x[2][x[3][i] : x[3][i + 1], None]), slices))[:, 0]
    pieces = 2 * slices
    ends = [nodes.size * i // pieces for i in range(pieces + 1)]

    def met(x, i):
        nodes, contexts, share, ends = x
        others = contexts.points(0, contexts.size)
        return np.concatenate([np.zeros((0, 1 + others.shape[1])), *(pair_table(nodes.points(a, min(a + 64, ends[i + 1])), others, share) for a in range(ends[i], ends[i + 1], 64))])

    return nodes, np.concatenate(_sliced(spark, (nodes, contexts, share, ends), met, pieces))


def _sliced(spark: SparkSession, given, f: Callable, slices: int) -> list[np.ndarray]:
    """f(given, i) of each slice, made on the executors, in order."""
    sent = spark.sparkContext.broadcast(given)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in batch.column(0).to_pylist():
                out = f(sent.value, i)
                yield pa.RecordBatch.from_arrays([pa.array([i]), pa.array([out.shape[1]]), pa.array([out.tobytes()], pa.binary())], ["i", "columns", "found"])

    rows = spark.range(0, slices, 1, slices).mapInArrow(run, "i long, columns long, found binary").collect()
    sent.destroy()
    return [np.frombuffer(r.found).reshape(-1, r.columns) for r in sorted(rows, key=lambda r: r.i)]
