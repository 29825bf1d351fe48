"""The forward path over blocks of ticks: [batch, sensors, width] arrays on the tape.

``rewrites`` computes each projection once per node or edge, splits scores of concatenations into a
node part and an edge part, and uses the factored time-shift score.  Without it the printed
equations are evaluated pair by pair, as the oracle.
"""

from __future__ import annotations

import numpy as np

from polyedge.models import autodiff as ad
from polyedge.models.autodiff import Var
from polyedge.models.config import ModelConfig
from polyedge.operators.forward import sinusoidal


def knn_incidence(z: np.ndarray, k: int) -> np.ndarray:
    """[edge, node] 0/1: each node with its k nearest, ties by id."""
    d = np.sqrt(np.maximum(((z[:, None] - z[None]) ** 2).sum(-1), 0))
    np.fill_diagonal(d, np.inf)
    h = np.eye(len(z))
    if k:
        near = np.argsort(d, axis=1, kind="stable")[:, :k]
        h[np.repeat(np.arange(len(z)), near.shape[1]), near.ravel()] = 1
    return h


def gumbel_incidence(z: np.ndarray, temperature: float, seed: int) -> np.ndarray:
    """Memberships by two-class Gumbel noise on similarity, with the integer noise of the relational form."""
    n = len(z)
    i, j = np.arange(n)[:, None], np.arange(n)
    d = np.sqrt(((z[:, None] - z[None]) ** 2).sum(-1))

    def noise(salt: int) -> np.ndarray:
        u = ((i * 7919 + j * 104729 + seed * 31 + salt * 15485863) % 99991 + 1) / 99993.0
        return -np.log(-np.log(u))

    h = (-d / temperature + 1 / temperature + noise(1) > noise(2)).astype(float)
    np.fill_diagonal(h, 1)
    return h


def incidence(z: np.ndarray, cfg: ModelConfig) -> np.ndarray:
    if cfg.structure == "irregular":
        scale = np.median(np.sqrt(((z[:, None] - z[None]) ** 2).sum(-1))) or 1.0
        return gumbel_incidence(z / scale, cfg.temperature, cfg.seed)
    h = knn_incidence(z, 1 if cfg.structure == "pair" else min(cfg.k, len(z) - 1))
    if cfg.symmetry == "union":
        h = np.maximum(h, h.T)
    elif cfg.symmetry == "mutual":
        h = np.minimum(h, h.T)
    return h


def _attend(scores: Var, mask: np.ndarray, axis: int, cfg: ModelConfig) -> Var:
    return ad.softmax(scores, axis, mask) if cfg.attention else ad.var(np.broadcast_to(mask, scores.shape).astype(float))


def _pair_score(flat: Var, z: Var, own: Var, m: Var, cfg: ModelConfig) -> Var:
    """ReLU of weights times concat(z_i, own_i, m_p): [batch, node, edge]."""
    d = cfg.d
    parts = [z, own] if cfg.use_z else [own]
    w = flat.reshape(-1)
    b, n = own.shape[:2]
    if not cfg.rewrites:
        rows = [ad.spread(p.reshape(1, n, 1, d) if p.value.ndim == 2 else p.reshape(b, n, 1, d), (b, n, m.shape[1], d)) for p in parts]
        rows.append(ad.spread(m.reshape(b, 1, m.shape[1], d), (b, n, m.shape[1], d)))
        return ad.relu((ad.concat(rows) * w).sum(-1))
    node = None
    for k, p in enumerate(parts):
        s = (p * w[k * d : (k + 1) * d]).sum(-1)
        node = s if node is None else node + s
    edge = (m * w[-d:]).sum(-1)
    node = node if node.value.ndim == 2 else node.reshape(1, -1)
    return ad.relu(node.reshape(node.shape[0], -1, 1) + edge.reshape(edge.shape[0], 1, -1))


def convolve(win: Var, h: np.ndarray, p: dict[str, Var], cfg: ModelConfig) -> tuple[Var, Var]:
    """Node features and edge features; ``win`` is [batch, n, w]."""
    u, own = win @ p["w_in"].swap(), win @ p["w_self"].swap()
    parts = ad.concat([ad.spread(p["z"].reshape(1, cfg.n, cfg.d), u.shape), u]) if cfg.use_z else u
    a = ad.relu((parts * p["a_member"].reshape(-1)).sum(-1))  # [b, n]: belongs to the node alone
    b = a.shape[0]
    alpha = _attend(ad.spread(a.reshape(b, 1, cfg.n), (b, cfg.n, cfg.n)), h, -1, cfg)  # [b, edge, node]
    e = ad.sigmoid(alpha @ u)
    m = e @ p["w_edge"].swap()
    score = _pair_score(p["a_edge"], p["z"], u, m, cfg)  # [b, node, edge]
    beta = _attend(score, h.T, -1, cfg)
    return ad.relu(own + beta @ m), e


def pool(x: Var, h: np.ndarray, p: dict[str, Var], cfg: ModelConfig) -> tuple[Var, np.ndarray]:
    """Pooled features on all nodes (zero rows for the rejected) and the 0/1 mask of kept nodes."""
    theta = p["theta"].reshape(-1)
    t = (x * theta).sum(-1)
    if cfg.score == "projection":
        norm = (ad.square(theta).sum()).value ** 0.5 + 1e-12
        s = t * (1.0 / norm)
    else:
        s = ad.softmax(t)
    keep = max(1, int(np.ceil(cfg.ratio * cfg.n - 1e-9)))
    order = np.argsort(-s.value, axis=-1, kind="stable")[:, :keep]
    mask = np.zeros(s.shape)
    np.put_along_axis(mask, order, 1.0, -1)
    gated = x * ad.relu(s).reshape(*s.shape, 1) if cfg.gate else x
    on = mask > 0
    sub = (h > 0) & on[:, :, None] & on[:, None, :]  # [b, edge, node]
    v = gated @ p["p_node"].swap()
    m = ad.sigmoid(ad.var(sub) @ v) @ p["p_edge"].swap()
    score = _pair_score(p["a_pool"], p["z"], v, m, cfg)
    zeta = _attend(score, np.swapaxes(sub, 1, 2), -1, cfg)
    return ad.sigmoid(v + zeta @ m) * mask[:, :, None], mask


def refine(x: Var, pooled: Var, mask: np.ndarray, h: np.ndarray, p: dict[str, Var], cfg: ModelConfig) -> Var:
    if cfg.skip == "add":
        y = pooled + x
    elif cfg.skip == "fill":
        y = pooled + x * (1 - mask)[:, :, None]
    else:
        y = pooled
    v = y @ p["u_node"].swap()
    m = ad.sigmoid(ad.var(h[None]) @ v) @ p["u_edge"].swap()
    sm = m @ p["u_shift"].swap()
    b, n = v.shape[:2]
    if cfg.shift == "difference" and cfg.rewrites:
        delta = ad.spread(ad.square(sm).sum(-1).reshape(b, 1, n), (b, n, n))
    else:
        mixed = ad.concat([ad.spread(p["z"].reshape(1, n, cfg.d), v.shape), v]) if cfg.use_z else v
        sg = (mixed @ p["u_mix"].swap()) @ p["u_shift"].swap()
        if cfg.shift == "dot":
            delta = sg @ sm.swap()
        else:
            a, c = sm.reshape(b, 1, n, cfg.d), sg.reshape(b, n, 1, cfg.d)
            delta = ((a - c) * (a + c)).sum(-1)
    gamma = _attend(delta, h.T, -1, cfg)
    return v + gamma @ m


def features(win: np.ndarray, h: np.ndarray, p: dict[str, Var], cfg: ModelConfig) -> Var:
    """[batch, n*d]: embedded node features that the heads read."""
    x = ad.var(win)
    if cfg.position == "sinusoidal":
        x = x + sinusoidal(cfg.n, cfg.w)
    elif cfg.position in ("learned", "neighbourhood"):
        pos = p["pos"]
        if cfg.position == "neighbourhood":
            off = 1 - np.eye(cfg.n)
            local = h * off
            local = np.where(local.sum(1, keepdims=True) > 0, local / np.maximum(local.sum(1, keepdims=True), 1), np.eye(cfg.n))
            glob = h.T / np.maximum(h.T.sum(1, keepdims=True), 1)
            pos = (pos + ad.var(local) @ pos + ad.var(glob) @ pos) * (1 / 3)
        x = x + pos
    c, _ = convolve(x, h, p, cfg)
    pooled, mask = pool(c, h, p, cfg)
    r = refine(c, pooled, mask, h, p, cfg)
    return (r * p["z"].reshape(1, cfg.n, cfg.d)).reshape(win.shape[0], cfg.n * cfg.d)


def _head(f: Var, p: dict[str, Var], w: str, b: str, cfg: ModelConfig) -> Var:
    for i in range(len(cfg.hidden)):
        f = ad.relu(f @ p[f"{w}_h{i}"].swap() + p[f"{w}_c{i}"])
    return f @ p[w].swap() + p[b]


def forecast(win: np.ndarray, h: np.ndarray, p: dict[str, Var], cfg: ModelConfig) -> Var:
    return _head(features(win, h, p, cfg), p, "head_w", "head_b", cfg)


def classify(win: np.ndarray, h: np.ndarray, p: dict[str, Var], cfg: ModelConfig) -> Var:
    return ad.sigmoid(_head(features(win, h, p, cfg), p, "cls_w", "cls_b", cfg)).reshape(-1)


def mse(pred: Var, y: np.ndarray) -> Var:
    return ad.square(pred - y).mean()


def bce(prob: Var, y: np.ndarray) -> Var:
    p = Var(np.clip(prob.value, 1e-7, 1 - 1e-7), (prob,), lambda g: (g,))
    return -(ad.log(p) * y + ad.log(1 - p) * (1 - y)).mean()


def as_vars(params: dict[str, np.ndarray]) -> dict[str, Var]:
    return {k: Var(v) for k, v in params.items()}
