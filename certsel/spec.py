"""What a user asks for: goal, target, failure probability, label budget and method."""

from __future__ import annotations

import math
import warnings
from dataclasses import dataclass, replace

#: Scores are integers on this grid; a cut-off above it selects nothing by score.
GRID = 1_000_000
NOTHING = GRID + 1
METHODS = ("uniform_raw", "uniform", "weighted", "onestage", "twostage", "exhaustive", "everything", "nothing")
BOUNDS = ("normal", "hoeffding", "bootstrap", "clopper_pearson", "student")


@dataclass(frozen=True)
class SelectionSpec:
    goal: str = "recall"
    target: float = 0.9
    delta: float = 0.05
    budget: int = 1000
    method: str = "weighted"
    seed: int = 0
    mix: float = 0.1
    exponent: float = 0.5
    step: int = 100
    bound: str = "normal"
    draws: str = "distinct"  # of uniform samples: distinct or iid; of weighted ones poisson draws in one map (single runs)
    stage2_weighting: str = "ratio"  # ratio or plain
    union_terms: str = "budget"  # budget or actual
    overflow: str = "guarded"  # or sample_min: what a recall goal does where too few matches were drawn for its bounds
    drop_known_negatives: bool = False
    allow_no_mix: bool = False

    def __post_init__(self):
        ok = (self.goal in ("recall", "precision"), 0 < self.target <= 1, 0 < self.delta < 1, self.budget > 0, self.method in METHODS, 0 <= self.mix <= 1,
              0 <= self.exponent <= 1, self.step > 0, self.bound in BOUNDS, self.draws in ("distinct", "iid", "poisson"), self.stage2_weighting in ("ratio", "plain"),
              self.union_terms in ("budget", "actual"), self.overflow in ("sample_min", "guarded"))
        if not all(ok):
            raise ValueError(f"not a valid selection: {self}")
        if self.goal == "recall" and self.method in ("onestage", "twostage"):
            raise ValueError("one-stage and two-stage sampling serve precision goals")
        if self.mix == 0 and self.exponent > 0 and self.is_weighted and not self.allow_no_mix:
            raise ValueError("without a uniform share, matches with score 0 are never drawn and the recall guarantee is void")
        if self.bound == "clopper_pearson" and self.is_weighted:
            raise ValueError("the exact binomial bound needs a uniform sample")
        if self.goal == "precision" and self.is_weighted and self.bound == "hoeffding":
            raise ValueError("a weighted precision is a ratio, which this bound does not cover")
        if self.method == "twostage" and self.bound not in ("normal", "student"):
            raise ValueError("two-stage sampling takes normal and student bounds")
        if self.budget <= 100:
            warnings.warn("bounds are asymptotic: more than 100 labels are advised", stacklevel=2)

    @property
    def is_weighted(self) -> bool:
        return self.method in ("weighted", "onestage", "twostage")

    def but(self, **changes) -> SelectionSpec:
        return replace(self, **changes)

    @property
    def grid_tests(self) -> int:
        return math.ceil(self.budget / self.step)


def tail(delta: float) -> float:
    """Multiplier of the normal-tail bound: sqrt(2 ln(1/delta))."""
    return math.sqrt(2 * math.log(1 / delta))
