"""Step rules, distances between successive weights, and the stop rule."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np

STEPS = {
    "constant": lambda beta, i: beta,
    "inv_sqrt": lambda beta, i: beta / np.sqrt(i),
    "inv": lambda beta, i: beta / i,
    "inv_sq": lambda beta, i: beta / (i * i),
}
#: The power q of i in beta / i^q.
STEP_POWER = {"constant": 0.0, "inv_sqrt": 0.5, "inv": 1.0, "inv_sq": 2.0}
STEP_SQL = {"constant": "{b}", "inv_sqrt": "{b}/sqrt({i})", "inv": "{b}/({i})", "inv_sq": "{b}/(({i})*({i}))"}

NORMS = {
    "l1": lambda d: float(np.abs(d).sum()),
    "l2": lambda d: float(np.sqrt((d * d).sum())),
    "linf": lambda d: float(np.abs(d).max()) if len(d) else 0.0,
}


def register_norm(name: str, of_difference) -> None:
    """A user's Converge: a function of new minus old weights."""
    NORMS[name] = of_difference


def smooth_bound_step(top_eigenvalue: float) -> float:
    """1/L, below which batch descent on an L-smooth convex function always descends."""
    return 1.0 / top_eigenvalue


def theoretical_bound(w0: np.ndarray, w_star: np.ndarray, alpha: float, eps: float) -> int:
    """Iterations that suffice for a convex smooth function at a step up to 1/L; needs the optimum, so it checks runs afterwards."""
    d = np.asarray(w0, dtype=float) - np.asarray(w_star, dtype=float)
    return int(np.ceil(float(d @ d) / (2 * alpha * eps)))


@dataclass
class LoopRule:
    """Whether to go on, from the last delta, the iteration and the clock; ``patience`` deltas in a row must be small."""

    tolerance: float = 1e-3
    max_iter: int = 1000
    time_budget: float | None = None
    patience: int = 1
    status: str = "RUNNING"
    _small: int = 0
    _began: float = field(default_factory=time.monotonic)

    def should_continue(self, delta: float | None, i: int) -> bool:
        if delta is not None:
            if not np.isfinite(delta) or delta > 1e12:
                self.status = "DIVERGED"
                return False
            self._small = self._small + 1 if delta < self.tolerance else 0
            if self._small >= self.patience:
                self.status = "CONVERGED"
                return False
        if i >= self.max_iter:
            self.status = "MAX_ITER"
            return False
        if self.time_budget is not None and time.monotonic() - self._began >= self.time_budget:
            self.status = "TIME"
            return False
        return True
