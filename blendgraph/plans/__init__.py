"""Plan choices and cost estimates."""

from .planner import RULES, GraphStats, choose, estimate, explain

__all__ = ["RULES", "GraphStats", "choose", "estimate", "explain"]
