"""Parameters: seeded or formula weights, saved as rows."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from polyedge.models.config import ModelConfig

#: name: rows, columns (in n, d, w) and salt of the formula weights
SHAPES = {
    "z": ("n", "d", 1),
    "pos": ("n", "w", 2),
    "w_in": ("d", "w", 3),
    "a_member": ("1", "2d", 4),
    "w_self": ("d", "w", 5),
    "w_edge": ("d", "d", 6),
    "a_edge": ("1", "3d", 7),
    "theta": ("1", "d", 8),
    "p_node": ("d", "d", 9),
    "p_edge": ("d", "d", 10),
    "a_pool": ("1", "3d", 11),
    "u_node": ("d", "d", 12),
    "u_edge": ("d", "d", 13),
    "u_mix": ("d", "2d", 14),
    "u_shift": ("d", "d", 15),
    "head_w": ("n", "nd", 16),
    "cls_w": ("1", "nd", 17),
}


def shape(name: str, cfg: ModelConfig) -> tuple[int, int]:
    size = {"n": cfg.n, "d": cfg.d, "w": cfg.w, "1": 1, "2d": 2 * cfg.d, "3d": 3 * cfg.d, "nd": cfg.n * cfg.d}
    if not cfg.use_z:
        if name in ("a_member", "u_mix"):
            return size[SHAPES[name][0]], cfg.d
        if name in ("a_edge", "a_pool"):
            return 1, 2 * cfg.d
    return size[SHAPES[name][0]], size[SHAPES[name][1]]


def formula(cfg: ModelConfig) -> dict[str, np.ndarray]:
    """Weights by integer arithmetic, equal in every engine."""
    out = {}
    for name, (_, _, salt) in SHAPES.items():
        r, c = shape(name, cfg)
        i, j = np.arange(r)[:, None], np.arange(c)
        out[name] = ((i * 37 + j * 61 + salt * 101 + i * j * 7) % 199 - 99) / (100 * np.sqrt(c))
    return out


def init(cfg: ModelConfig) -> dict[str, np.ndarray]:
    rng = np.random.default_rng(cfg.seed)
    out = {}
    for name in SHAPES:
        r, c = shape(name, cfg)
        gain = 1.0 if name == "z" else 0.05 if name == "pos" else 1 / np.sqrt(c)
        out[name] = rng.normal(0, gain, (r, c))
    # z multiplies in the heads: near one, so that the heads see the features from the start
    out["z"] = 1 + 0.3 * rng.normal(0, 1, out["z"].shape)
    out["head_b"] = np.zeros(cfg.n)
    out["cls_b"] = np.zeros(1)
    return out


def save(spark: SparkSession, params: dict[str, np.ndarray], path: str, run_id: str, epoch: int) -> None:
    rows = [(run_id, epoch, k, list(v.shape), [float(x) for x in v.ravel()]) for k, v in params.items()]
    spark.createDataFrame(rows, "run_id string, epoch int, name string, shape array<int>, data array<double>").coalesce(1).write.mode("append").parquet(path)


def load(saved: DataFrame, run_id: str, epoch: int) -> dict[str, np.ndarray]:
    rows = saved.where((saved.run_id == run_id) & (saved.epoch == epoch)).collect()
    return {r["name"]: np.array(r["data"]).reshape(r["shape"]) for r in rows}
