"""Predictive control: search for values of one manipulated sensor that return the system to normal."""

from __future__ import annotations

from dataclasses import dataclass
from itertools import product

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from polyedge.models import blockmath as bm
from polyedge.models.config import ModelConfig
from polyedge.session import ship


@dataclass(frozen=True)
class Search:
    population: int = 64
    generations: int = 50
    tournament: int = 3
    elite: int = 2
    mutation: float = 0.15
    low: float = 0.0
    high: float = 1.0
    seed: int = 1


@dataclass(frozen=True)
class Context:
    """A trained model, the last w readings [w, n], what the plant should read and robust scales."""

    params: dict
    cfg: ModelConfig
    history: np.ndarray
    expected: np.ndarray  # [horizon, n]
    med: np.ndarray
    iqr: np.ndarray
    sensor: int


def fitness(genes: np.ndarray, ctx: Context, objective: str = "score") -> np.ndarray:
    """Loss of each candidate sequence [m, horizon]: the model rolls forward with the genes spliced in.

    ``score``: the greatest robust deviation from the forecast; ``tracking``: distance of the
    forecasts of the other sensors to the expected readings.
    """
    h = bm.incidence(ctx.params["z"], ctx.cfg)
    p = bm.as_vars(ctx.params)
    m, horizon = genes.shape
    rows = np.repeat(ctx.history[None], m, 0)
    worst, off = np.zeros(m), np.zeros(m)
    others = np.arange(ctx.cfg.n) != ctx.sensor
    for t in range(horizon):
        pred = bm.forecast(np.swapaxes(rows, 1, 2), h, p, ctx.cfg).value
        now = np.repeat(ctx.expected[t][None], m, 0)
        now[:, ctx.sensor] = genes[:, t]
        score = (np.abs(pred - now) - ctx.med) / np.maximum(ctx.iqr, 1e-6)
        worst = np.maximum(worst, score.max(1))
        off += np.abs(pred - ctx.expected[t])[:, others].mean(1)
        rows = np.concatenate([rows[:, 1:], now[:, None]], 1)
    return worst if objective == "score" else off / horizon


def evolve(genes: np.ndarray, loss: np.ndarray, s: Search, rng: np.random.Generator) -> np.ndarray:
    """Elites, tournament parents, blend crossover, Gaussian mutation, bounds."""
    order = np.argsort(loss, kind="stable")
    out = [genes[i] for i in order[: s.elite]]
    while len(out) < len(genes):
        a, b = (min(rng.integers(0, len(genes), s.tournament), key=lambda i: loss[i]) for _ in range(2))
        mix = rng.uniform(-0.25, 1.25, genes.shape[1])
        child = mix * genes[a] + (1 - mix) * genes[b]
        child = child + rng.normal(0, s.mutation * (s.high - s.low), len(child)) * (rng.random(len(child)) < 0.3)
        out.append(np.clip(child, s.low, s.high))
    return np.stack(out)


def search(ctx: Context, horizon: int = 1, objective: str = "score", s: Search | None = None, stop_at: float | None = None) -> tuple[np.ndarray, float, list[float]]:
    """Best sequence, its loss and the best loss of every generation; stops below ``stop_at``."""
    s = s or Search()
    rng = np.random.default_rng(s.seed)
    genes = rng.uniform(s.low, s.high, (s.population, horizon))
    history: list[float] = []
    best, best_loss = genes[0], np.inf
    for _ in range(s.generations):
        loss = fitness(genes, ctx, objective)
        i = int(loss.argmin())
        if loss[i] < best_loss:
            best, best_loss = genes[i].copy(), float(loss[i])
        history.append(best_loss)
        if stop_at is not None and best_loss < stop_at:
            break
        genes = evolve(genes, loss, s, rng)
    return best, best_loss, history


def grid(ctx: Context, horizon: int = 1, steps: int = 41, objective: str = "score", low: float = 0.0, high: float = 1.0) -> tuple[np.ndarray, float]:
    """Exhaustive search over discrete values."""
    genes = np.array(list(product(np.linspace(low, high, steps), repeat=horizon)))
    loss = np.concatenate([fitness(genes[i : i + 2048], ctx, objective) for i in range(0, len(genes), 2048)])
    i = int(loss.argmin())
    return genes[i], float(loss[i])


def search_many(spark: SparkSession, contexts: list[Context], horizon: int = 1, objective: str = "score", s: Search | None = None) -> DataFrame:
    """One search per incident, all incidents in parallel as rows of one job."""
    ship(spark)
    held = spark.sparkContext.broadcast((contexts, horizon, objective, s or Search()))

    def run(frames):
        contexts, horizon, objective, s = held.value
        for f in frames:
            rows = []
            for i in f["incident"]:
                c = contexts[int(i)]
                best, loss, history = search(c, horizon, objective, s)
                before = fitness(np.repeat(c.history[-1:, c.sensor][None], horizon, 1), c, objective)[0]
                rows.append((int(i), c.sensor, float(c.history[-1, c.sensor]), [float(x) for x in best], float(before), loss, len(history)))
            yield pd.DataFrame(rows, columns=["incident", "sensor", "current", "recommended", "before", "after", "generations"])

    ids = spark.range(len(contexts)).withColumnRenamed("id", "incident").repartition(max(1, min(len(contexts), 200)))
    return ids.mapInPandas(run, "incident long, sensor int, current double, recommended array<double>, before double, after double, generations int")
