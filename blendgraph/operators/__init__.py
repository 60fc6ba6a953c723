"""Relational operators that users of the methods need around them."""

from .relational import (
    band_join,
    co_bucketed_join,
    edges_between,
    exact_pairs,
    grouped_accuracy,
    next_event,
    salted_join,
    set_operations,
    top_links,
)

__all__ = ["band_join", "co_bucketed_join", "edges_between", "exact_pairs", "grouped_accuracy", "next_event", "salted_join", "set_operations", "top_links"]
