"""Joint training of structure and forecaster, and scoring of whole panels in Arrow blocks.

``exact`` runs the true sequence of small batches in one task, for panels that fit a worker; the
five seeds, or a whole sweep, fan out as rows of one job.  ``large_batch`` is for more data: every
task sums the gradient of its chunks, the sums meet in a tree, the driver takes one Adam step.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from polyedge.models import autodiff as ad, blockmath as bm, params as pm
from polyedge.models.config import ModelConfig
from polyedge.models.optim import Adam, EarlyStop, HalveOnPlateau
from polyedge.operators import panel as P
from polyedge.session import ship


TREE = 4


def windows(x: np.ndarray, w: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(targets' row numbers, windows [m, n, w], targets [m, n]) of consecutive rows [ticks, n]."""
    if len(x) <= w:
        return np.empty(0, int), np.empty((0, x.shape[1] if x.ndim == 2 else 0, w)), np.empty((0, x.shape[1] if x.ndim == 2 else 0))
    view = np.lib.stride_tricks.sliding_window_view(x, w, axis=0)[:-1]
    return np.arange(w, len(x)), view, x[w:]


def initial(cfg: ModelConfig) -> dict[str, np.ndarray]:
    p = pm.init(cfg)
    rng = np.random.default_rng(cfg.seed + 1)
    for name, out in (("head_w", cfg.n), ("cls_w", 1)):
        width = cfg.n * cfg.d
        for i, h in enumerate(cfg.hidden):
            p[f"{name}_h{i}"] = rng.normal(0, 1 / np.sqrt(width), (h, width))
            p[f"{name}_c{i}"] = np.zeros(h)
            width = h
        p[name] = rng.normal(0, 0.1 / np.sqrt(width), (out, width))
    return p


def loss_of(win: np.ndarray, y: np.ndarray, h: np.ndarray, cfg: ModelConfig):
    if cfg.head == "classify":
        return lambda p: bm.bce(bm.classify(win, h, p, cfg), y)
    return lambda p: bm.mse(bm.forecast(win, h, p, cfg), y)


def predict(win: np.ndarray, params: dict[str, np.ndarray], cfg: ModelConfig, block: int = 256) -> np.ndarray:
    h = bm.incidence(params["z"], cfg)
    p = bm.as_vars(params)
    f = bm.classify if cfg.head == "classify" else bm.forecast
    parts = [f(win[i : i + block], h, p, cfg).value for i in range(0, len(win), block)]
    return np.concatenate(parts) if parts else np.empty((0, cfg.n))


def mean_loss(win: np.ndarray, y: np.ndarray, h: np.ndarray, params: dict[str, np.ndarray], cfg: ModelConfig, block: int = 256) -> float:
    """Loss over all rows, block by block: the arrays of one block are [block, n, n]."""
    p = bm.as_vars(params)
    return sum(float(loss_of(win[i : i + block], y[i : i + block], h, cfg)(p).value) * len(y[i : i + block]) for i in range(0, len(y), block)) / len(y)


def fit(x: np.ndarray, n_train: int, n_validation: int, cfg: ModelConfig, labels: np.ndarray | None = None, epochs: int = 100, batch: int = 48, lr: float = 1e-3, patience: int = 20) -> tuple[dict[str, np.ndarray], list[float]]:
    """Exact small-batch training on rows [ticks, n]; the structure is learned anew every epoch."""
    at, win, y = windows(x, cfg.w)
    if labels is not None:
        y = labels[at]
    train, val = at < n_train, (at >= n_train) & (at < n_train + n_validation)
    params = initial(cfg)
    opt, halve, stop = Adam(lr), HalveOnPlateau(), EarlyStop(patience)
    rng = np.random.default_rng(cfg.seed)
    rows, history = np.flatnonzero(train), []
    # rows of one part follow each other: a slice is a view, a mask would copy w times the panel
    checked = np.flatnonzero(val) if val.any() else rows
    check = slice(checked[0], checked[-1] + 1) if len(checked) else slice(0, 0)
    used = {k for k in params if not k.startswith("cls" if cfg.head == "forecast" else "head")}
    for _ in range(epochs):
        h = bm.incidence(params["z"], cfg)
        order = rng.permutation(rows)
        for i in range(0, len(order), batch):
            k = order[i : i + batch]
            _, g = ad.gradients(loss_of(win[k], y[k], h, cfg), {n: params[n] for n in used})
            opt.step(params, g)
        h = bm.incidence(params["z"], cfg)
        loss = mean_loss(win[check], y[check], h, params, cfg)
        history.append(loss)
        halve.update(loss, opt)
        if stop.update(loss, params):
            break
    return stop.kept or params, history


def chunk_rows(vectors: DataFrame, w: int, chunk: int) -> DataFrame:
    """(chunk, own, tick, x): ticks dealt to chunks, each with the w ticks before it."""
    own = F.floor(F.col("tick") / chunk).cast("bigint")
    last = F.floor((F.col("tick") + w) / chunk).cast("bigint")
    dealt = vectors.withColumn("chunk", F.explode(F.sequence(own, last)))
    return dealt.withColumn("own", F.col("chunk") == F.floor(F.col("tick") / chunk)).select("chunk", "own", "tick", "x")


def _blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(ticks, own, x) of one chunk at a time from rows sorted by chunk and tick."""
    held: list[tuple] = []
    for b in batches:
        for c, own, t, x in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist(), b.column(3), strict=True):
            if held and held[0][0] != c:
                yield np.array([h[2] for h in held]), np.array([h[1] for h in held]), np.array([h[3] for h in held])
                held = []
            held.append((c, own, t, x.values.to_numpy(zero_copy_only=False)))
    if held:
        yield np.array([h[2] for h in held]), np.array([h[1] for h in held]), np.array([h[3] for h in held])


def score_blocks(vectors: DataFrame, params: dict[str, np.ndarray], cfg: ModelConfig, chunk: int = 512) -> DataFrame:
    """(tick, sensor_id, y, y_hat), or (tick, p) of the classifier: windows exist only inside a batch."""
    spark = vectors.sparkSession
    ship(spark)
    held = spark.sparkContext.broadcast((params, cfg))

    def run(batches):
        params, cfg = held.value
        for ticks, own, x in _blocks(batches):
            at, win, y = windows(x, cfg.w)
            on = own[at] if len(at) else np.empty(0, bool)
            if not on.any():
                continue
            out = predict(win[on], params, cfg)
            t = ticks[at[on]]
            if cfg.head == "classify":
                yield pa.RecordBatch.from_arrays([pa.array(t), pa.array(out)], names=["tick", "p"])
            else:
                n = out.shape[1]
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(t, n)), pa.array(np.tile(np.arange(n, dtype=np.int32), len(t))), pa.array(y[on].ravel()), pa.array(out.ravel())], names=["tick", "sensor_id", "y", "y_hat"])

    rows = chunk_rows(vectors, cfg.w, chunk).repartition("chunk").sortWithinPartitions("chunk", "tick")
    schema = "tick long, p double" if cfg.head == "classify" else "tick long, sensor_id int, y double, y_hat double"
    return rows.mapInArrow(run, schema)


def gradient_round(chunks: DataFrame, params: dict[str, np.ndarray], cfg: ModelConfig, n_train: int) -> tuple[float, dict[str, np.ndarray]]:
    """Mean loss and gradient over all training windows: one row per task, summed in a tree."""
    spark = chunks.sparkSession
    held = spark.sparkContext.broadcast((params, cfg, n_train))
    names = sorted(k for k in params if not k.startswith("cls"))

    def run(batches):
        params, cfg, n_train = held.value
        total, count, loss = None, 0, 0.0
        h = bm.incidence(params["z"], cfg)
        for ticks, own, x in _blocks(batches):
            at, win, y = windows(x, cfg.w)
            k = np.flatnonzero(own[at] & (ticks[at] < n_train)) if len(at) else np.empty(0, int)
            for i in range(0, len(k), 256):
                j = k[i : i + 256]
                value, g = ad.gradients(loss_of(win[j], y[j], h, cfg), {n: params[n] for n in names})
                flat = np.concatenate([g[n].ravel() for n in names]) * len(j)
                total = flat if total is None else total + flat
                count, loss = count + len(j), loss + value * len(j)
        if count:
            yield pa.RecordBatch.from_arrays([pa.array([float(count)]), pa.array([loss]), pa.array([total])], names=["n", "loss", "g"])

    parts = chunks.mapInArrow(run, "n double, loss double, g array<double>")

    def add(rows):
        total = None
        for b in rows:
            for n, loss, g in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2), strict=True):
                v = np.concatenate([[n, loss], g.values.to_numpy(zero_copy_only=False)])
                total = v if total is None else total + v
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([total[0]]), pa.array([total[1]]), pa.array([total[2:]])], names=["n", "loss", "g"])

    tree = parts.repartition(TREE).mapInArrow(add, "n double, loss double, g array<double>")
    rows = tree.collect()
    n = sum(r["n"] for r in rows)
    flat = np.sum([r["g"] for r in rows], axis=0) / n
    out, i = {}, 0
    for k in names:
        size = params[k].size
        out[k] = flat[i : i + size].reshape(params[k].shape)
        i += size
    return sum(r["loss"] for r in rows) / n, out


def fit_large_batch(vectors: DataFrame, n_train: int, cfg: ModelConfig, rounds: int = 20, lr: float = 5e-3, chunk: int = 512) -> tuple[dict[str, np.ndarray], list[float]]:
    """One summed gradient and one Adam step a round; the driver holds parameters only."""
    ship(vectors.sparkSession)
    chunks = chunk_rows(vectors, cfg.w, chunk).repartition("chunk").sortWithinPartitions("chunk", "tick").persist()
    params, opt, history = initial(cfg), Adam(lr), []
    try:
        for _ in range(rounds):
            loss, g = gradient_round(chunks, params, cfg, n_train)
            opt.step(params, g)
            history.append(loss)
    finally:
        chunks.unpersist()
    return params, history


def matrix(p: DataFrame) -> np.ndarray:
    """Rows [ticks, n] of a panel that fits the driver (exact training only)."""
    v = P.to_vectors(p).select("tick", "x").orderBy("tick").toPandas()
    return np.stack(v["x"].to_numpy()) if len(v) else np.empty((0, 0))


def fit_panel(p: DataFrame, cfg: ModelConfig, train: float = 0.6, validation: float = 0.2, **options) -> tuple[dict[str, np.ndarray], ModelConfig, list[float]]:
    x = matrix(p)
    cfg = replace(cfg, n=x.shape[1]).capped()
    a = int(np.floor(len(x) * train))
    params, history = fit(x, a, int(np.floor(len(x) * (train + validation))) - a, cfg, **options)
    return params, cfg, history
