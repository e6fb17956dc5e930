"""Step rules: what to subtract from the parameters for a gradient at step t (from 1)."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np


@dataclass
class StepRule:
    kind: str = "constant"
    eta: float = 0.1
    t0: float = 1.0
    mu: float = 0.9
    eps: float = 1e-8
    _memory: np.ndarray | None = field(default=None, repr=False)

    def rate(self, t: int) -> float:
        return {"inverse_step": self.eta * self.t0 / (self.t0 + t), "inverse_sqrt": self.eta / math.sqrt(max(t, 1))}.get(self.kind, self.eta)

    def move(self, gradient: np.ndarray, t: int) -> np.ndarray:
        if self.kind == "momentum":
            self._memory = gradient if self._memory is None else self.mu * self._memory + gradient
            return self.eta * self._memory
        if self.kind == "per_coordinate":
            self._memory = gradient**2 if self._memory is None else self._memory + gradient**2
            return self.eta * gradient / (np.sqrt(self._memory) + self.eps)
        return self.rate(t) * gradient


def constant(eta: float) -> StepRule:
    return StepRule("constant", eta)


def inverse_step(eta: float, t0: float = 100.0) -> StepRule:
    return StepRule("inverse_step", eta, t0=t0)


def inverse_sqrt(eta: float) -> StepRule:
    return StepRule("inverse_sqrt", eta)


def momentum(eta: float, mu: float = 0.9) -> StepRule:
    return StepRule("momentum", eta, mu=mu)


def per_coordinate(eta: float, eps: float = 1e-8) -> StepRule:
    return StepRule("per_coordinate", eta, eps=eps)
