"""Adam, learning-rate halving on a plateau and early stopping."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np


@dataclass
class Adam:
    lr: float = 1e-3
    b1: float = 0.9
    b2: float = 0.99
    eps: float = 1e-8
    t: int = 0
    m: dict[str, np.ndarray] = field(default_factory=dict)
    v: dict[str, np.ndarray] = field(default_factory=dict)

    def step(self, params: dict[str, np.ndarray], grads: dict[str, np.ndarray]) -> None:
        self.t += 1
        for k, g in grads.items():
            m = self.m[k] = self.b1 * self.m.get(k, 0.0) + (1 - self.b1) * g
            v = self.v[k] = self.b2 * self.v.get(k, 0.0) + (1 - self.b2) * g * g
            params[k] = params[k] - self.lr * (m / (1 - self.b1**self.t)) / (np.sqrt(v / (1 - self.b2**self.t)) + self.eps)


@dataclass
class HalveOnPlateau:
    """Halve the rate after ``patience`` epochs without gain on validation."""

    patience: int = 10
    best: float = np.inf
    waited: int = 0

    def update(self, loss: float, opt: Adam) -> None:
        if loss < self.best - 1e-12:
            self.best, self.waited = loss, 0
            return
        self.waited += 1
        if self.waited >= self.patience:
            opt.lr, self.waited = opt.lr / 2, 0


@dataclass
class EarlyStop:
    """Stop after ``patience`` epochs without gain; keeps the best parameters."""

    patience: int = 20
    best: float = np.inf
    waited: int = 0
    kept: dict[str, np.ndarray] | None = None

    def update(self, loss: float, params: dict[str, np.ndarray]) -> bool:
        if loss < self.best - 1e-12:
            self.best, self.waited, self.kept = loss, 0, {k: v.copy() for k, v in params.items()}
        else:
            self.waited += 1
        return self.waited >= self.patience
