"""Parameters of the methods."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class WalkConfig:
    """Random walks and pair counts. window is the largest counted offset; window_rule 'strict' leaves it out."""

    walk_length: int = 40
    per_node: int = 10
    window: int = 5
    pair_mode: str = "all"
    direction: str = "both"
    window_rule: str = "inclusive"
    include_self: bool = False
    start: str = "uniform"
    seed: int = 7

    def __post_init__(self):
        if self.walk_length < 2 or self.per_node < 1 or self.window < 1:
            raise ValueError("a walk needs two nodes, a node one walk, a window one offset")
        for value, allowed in ((self.pair_mode, ("all", "sampled", "offset_uniform")), (self.direction, ("both", "forward")), (self.window_rule, ("inclusive", "strict")), (self.start, ("uniform", "stationary"))):
            if value not in allowed:
                raise ValueError(f"{value!r} is none of {allowed}")

    @property
    def offsets(self) -> range:
        """The counted offsets."""
        return range(0 if self.include_self else 1, min(self.window + (self.window_rule == "inclusive"), self.walk_length))


@dataclass(frozen=True)
class FitConfig:
    """Joint factorization. negatives is the k of the cap. step: 'fixed' uses step_size as it is, 'lipschitz' the step that
    the curvature's bound makes safe, 'search' (features) and 'backtracking' (both halves) longer ones that the loss
    agrees to. negative_mode 'exact' looks at all pairs, 'sampled' at draws_per_node of each node beside its counts."""

    dim: int = 16
    negatives: float = 1.0
    max_outer: int = 20
    max_inner: int = 3
    tol: float = 1e-4
    step: str = "search"
    step_size: float = 1e-7
    negative_mode: str = "sampled"
    draws_per_node: int = 64
    loss: str = "sgns"
    ridge: float = 0.0
    seed: int = 7

    def __post_init__(self):
        for value, allowed in ((self.step, ("fixed", "lipschitz", "search", "backtracking")), (self.negative_mode, ("exact", "sampled")), (self.loss, ("sgns", "squared", "logistic_uncapped"))):
            if value not in allowed:
                raise ValueError(f"{value!r} is none of {allowed}")

    def with_(self, **changes) -> FitConfig:
        return replace(self, **changes)


#: The published settings, a quick one for tests and the one whose single step SQL can follow.
PAPER = FitConfig(dim=200, max_outer=200, max_inner=1, step="fixed", step_size=1e-7)
FAST = FitConfig(dim=16, max_outer=15, max_inner=2)
ORACLE = FitConfig(dim=4, max_outer=1, max_inner=1, step="lipschitz", negative_mode="exact")
