"""What the comparison detectors share: shapes, training of small networks, detection in numpy."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np

from polyedge.models import autodiff as ad
from polyedge.models.optim import Adam

Params = dict[str, np.ndarray]


def windows(x: np.ndarray, w: int) -> np.ndarray:
    """[T - w, w, n]: the w rows before each row from w on."""
    return np.swapaxes(np.lib.stride_tricks.sliding_window_view(x, w, axis=0)[:-1], 1, 2)


def fill_head(dev: np.ndarray, w: int) -> np.ndarray:
    """The first w rows, which have no window, get no deviation."""
    return np.concatenate([np.zeros((w, dev.shape[1])), dev])


def weights(rng: np.random.Generator, **shapes: tuple[int, ...]) -> Params:
    return {k: (np.zeros(s) if k.startswith("b") else rng.normal(0, 1 / np.sqrt(s[0]), s)) for k, s in shapes.items()}


def train(params: Params, loss: Callable[[dict[str, ad.Var], np.ndarray], ad.Var], rows: int, epochs: int = 8, batch: int = 48, lr: float = 5e-3, seed: int = 1) -> Params:
    """Adam over seeded small batches; ``loss`` takes the variables and row numbers."""
    rng, opt = np.random.default_rng(seed), Adam(lr)
    for _ in range(epochs):
        order = rng.permutation(rows)
        for i in range(0, rows, batch):
            _, g = ad.gradients(lambda p, k=order[i : i + batch]: loss(p, k), params)
            opt.step(params, g)
    return params


def frozen(params: Params) -> dict[str, ad.Var]:
    return {k: ad.Var(v) for k, v in params.items()}


def robust(dev: np.ndarray, rows: slice, eps: float = 1e-6) -> np.ndarray:
    q1, med, q3 = np.percentile(dev[rows], [25, 50, 75], axis=0)
    return (dev - med) / np.maximum(q3 - q1, eps)


def detect(dev: np.ndarray, n_train: int, n_validation: int, w_a: int = 10, first: int = 0) -> np.ndarray:
    """0/1 per row: robust scores, maximum, trailing mean from row ``first`` on, validation threshold."""
    a, b = n_train, n_train + n_validation
    top = robust(dev, slice(a, b)).max(1)
    total = np.cumsum(np.concatenate([[0.0], top[first:]]))
    n = np.arange(1, len(top) - first + 1)
    lo = np.maximum(0, n - w_a)
    smooth = np.concatenate([np.full(first, -np.inf), (total[n] - total[lo]) / (n - lo)])
    flag = (smooth > smooth[a:b].max()).astype(int)
    flag[:b] = 0
    return flag
