"""Parameters of graph recall; every default is ours, as none is printed in the reference."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace


@dataclass(frozen=True)
class RecallConfig:
    """n responses per anchor, threshold tau, k hops, budget of anchors per target; r walks of at most l edges, exploration alpha, quality eta."""

    n: int = 20
    tau: float = 0.2
    k: int = 3
    budget: int | None = 200
    conditioning: str = "soft"
    replace: bool = False
    short_pool: str = "empty"
    dedup_pool: bool = False
    norm: str = "extracted"
    strength_agg: str = "max"
    keep_return_edges: bool = False
    r: int = 50
    r_max: int = 800
    l: int = 4  # noqa: E741
    l_unit: str = "edges"
    alpha: float = 1.0
    eta: float = 0.25
    eta_mode: str = "quantile"
    self_avoiding: bool = False
    dedup_paths: bool = False
    weighting: str = "strength"
    tau_n: float | None = None
    start: str = "round_robin"
    answer: str = "start"
    obj_rule: str = "non_target"
    style: str = "qa"
    coverage_target: float = 0.9
    coverage_unit: str = "nodes"
    seed: int = 42

    def __post_init__(self):
        allowed = {
            "conditioning": ("soft", "strict", "none"), "short_pool": ("empty", "shrink"), "norm": ("extracted", "retained"), "strength_agg": ("max", "mean", "first"), "l_unit": ("edges", "nodes"),
            "eta_mode": ("absolute", "quantile"), "weighting": ("strength", "uniform"), "start": ("round_robin", "weighted"), "answer": ("start", "left"), "obj_rule": ("non_target", "literal"), "style": ("qa", "cloze", "statement"), "coverage_unit": ("nodes", "strength"),
        }
        for name, values in allowed.items():
            if getattr(self, name) not in values:
                raise ValueError(f"{name} is one of {values}")
        if not (self.n >= 1 and 0 < self.tau <= 1 and self.k >= 1 and self.r >= 1 and self.l >= 1 and self.alpha >= 0 and 0 <= self.eta <= 1 and 0 <= self.coverage_target <= 1):
            raise ValueError("a number is out of its range")
        if self.budget is not None and self.budget < 1:
            raise ValueError("budget is None or at least 1")

    @property
    def need(self) -> int:
        """Least number of responses that keeps a mention: s >= tau in whole numbers."""
        return math.ceil(self.tau * self.n - 1e-9)

    @property
    def max_edges(self) -> int:
        return self.l if self.l_unit == "edges" else self.l - 1

    def but(self, **changes) -> RecallConfig:
        return replace(self, **changes)
