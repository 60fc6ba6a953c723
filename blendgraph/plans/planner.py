"""Choices made before a plan is built, from statistics, as rules that explain themselves; and what a run will cost.

The engine's own optimiser takes care of pruning, pushdown and join order. What it cannot know is decided here.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import FitConfig, WalkConfig
from ..graph import degrees


@dataclass(frozen=True)
class GraphStats:
    nodes: int
    edges: int
    degree_squares: float
    max_degree: int
    content_entries: int = 0
    features: int = 0

    @classmethod
    def of(cls, edges: DataFrame, content: DataFrame | None = None) -> GraphStats:
        """One pass over the edges (and the content)."""
        r = degrees(edges).agg(F.count("*"), F.sum("degree"), F.sum(F.col("degree").cast("double") ** 2), F.max("degree")).first()
        c = content.agg(F.count("*"), F.approx_count_distinct("feature")).first() if content is not None else (0, 0)
        return cls(r[0] or 0, r[1] or 0, r[2] or 0.0, r[3] or 0, c[0], c[1])


@dataclass(frozen=True)
class Rule:
    name: str
    applies: Callable[[GraphStats, WalkConfig, FitConfig], bool]
    choice: tuple[str, str]
    text: str


BROADCAST_MB, DRIVER_MB = 64.0, 512.0

RULES = (
    Rule("proximity", lambda s, w, f: s.degree_squares <= 20 * s.edges, ("exact", "sampled"), "matrix powers if the second has at most 20 times the edges, else walks"),
    Rule("walks", lambda s, w, f: s.edges * 24 / 1e6 <= BROADCAST_MB, ("broadcast", "hops"), "send the adjacency if it is small, else join each step"),
    Rule("negatives", lambda s, w, f: float(s.nodes) ** 2 * f.dim <= 4e11, ("exact", "sampled"), "all pairs of a node in a task while their product is small"),
    Rule("context_side", lambda s, w, f: (24 * s.nodes + 16 * s.content_entries + 8 * s.nodes * f.dim) / 1e6 <= DRIVER_MB, ("broadcast", "joins"), "send the context dictionary if it is small, else join vectors to pairs"),
    Rule("adjacency", lambda s, w, f: s.max_degree <= 4096, ("one row", "chunks"), "a hub's neighbours lie in several rows"),
    Rule("symmetric_counts", lambda s, w, f: w.direction == "both", ("count once and mirror", "count as walked"), "count pairs forward and add the mirror image of the sums"),
)


def choose(stats: GraphStats, walks: WalkConfig = WalkConfig(), fit: FitConfig = FitConfig()) -> dict[str, str]:
    return {r.name: r.choice[0] if r.applies(stats, walks, fit) else r.choice[1] for r in RULES}


def explain(stats: GraphStats, walks: WalkConfig = WalkConfig(), fit: FitConfig = FitConfig()) -> str:
    chosen = choose(stats, walks, fit)
    return "\n".join(f"{r.name}: {chosen[r.name]} ({r.text})" for r in RULES)


def estimate(stats: GraphStats, walks: WalkConfig = WalkConfig(), fit: FitConfig = FitConfig()) -> dict[str, float]:
    """Rows and bytes that the stages will make."""
    n_walks = stats.nodes * walks.per_node
    forward = sum(walks.walk_length - k for k in walks.offsets if k)
    pairs = n_walks * forward * (2 if walks.direction == "both" else 1)
    counts = min(float(stats.nodes) ** 2, pairs)
    drawn = stats.nodes * fit.draws_per_node
    return {
        "walk_hops": n_walks * (walks.walk_length - 1),
        "pairs_per_walk": forward * (2 if walks.direction == "both" else 1),
        "pairs": pairs,
        "counts_at_most": counts,
        "walk_bytes": 8.0 * n_walks * walks.walk_length,
        "gradient_flops": 2.0 * fit.dim * (stats.content_entries + (float(stats.nodes) ** 2 if fit.negative_mode == "exact" else counts + drawn)),
    }
