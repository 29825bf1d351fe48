"""Structured Streaming: ticks, lateness, joins, deduplication and the online detector."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from polyedge.models import train as T
from polyedge.models.config import ModelConfig
from polyedge.session import ship


def ticks(df: DataFrame, every: str, key: str, value: str, ts: str = "ts", delay: str | None = None) -> DataFrame:
    """Tumbling sums per key; with ``delay`` the watermark closes windows and bounds the state."""
    rows = df.withWatermark(ts, delay) if delay else df
    got = rows.groupBy(F.window(ts, every).alias("w"), key).agg(F.sum(value).alias("value"), F.count("*").alias("n"))
    return got.select(F.col("w.start").alias("start"), key, "value", "n")


def sliding(df: DataFrame, length: str, step: str, ts: str = "ts") -> DataFrame:
    return df.groupBy(F.window(ts, length, step).alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(df: DataFrame, gap: str, key: str, ts: str = "ts", delay: str | None = None) -> DataFrame:
    rows = df.withWatermark(ts, delay) if delay else df
    return rows.groupBy(key, F.session_window(ts, gap).alias("w")).agg(F.count("*").alias("n")).select(key, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def dedup(df: DataFrame, id_col: str, delay: str, ts: str = "ts") -> DataFrame:
    return df.withWatermark(ts, delay).dropDuplicatesWithinWatermark([id_col])


def join_static(stream: DataFrame, static: DataFrame, on: str) -> DataFrame:
    return stream.join(static, on)


def join_stream(left: DataFrame, right: DataFrame, key: str, bound: str, delay: str) -> DataFrame:
    """Rows of both streams with one key and times within ``bound`` of each other."""
    a = left.withWatermark("ts", delay).alias("a")
    b = right.withWatermark("ts", delay).alias("b")
    near = F.expr(f"a.{key} = b.{key} AND b.ts BETWEEN a.ts - INTERVAL {bound} AND a.ts")
    return a.join(b, near).select(F.col(f"a.{key}").alias(key), F.col("a.ts").alias("ts"), F.col("b.ts").alias("other_ts"))


def with_lateness(df: DataFrame, batch_watermark: str, ts: str = "ts") -> tuple[DataFrame, DataFrame]:
    """Inside ``foreachBatch``: rows in time and late rows, for the main and the side sink."""
    on = F.col(ts) >= F.to_timestamp(F.lit(batch_watermark))
    return df.where(on), df.where(~on)


class OnlineDetector:
    """One decision per tick: a ring of the last w vectors and of the last w_a scores per plant."""

    def __init__(self, params: dict, cfg: ModelConfig, med: np.ndarray, iqr: np.ndarray, threshold: float):
        self.params, self.cfg = params, cfg
        self.med, self.iqr, self.threshold = med, iqr, threshold

    def run(self, ring: np.ndarray, scores: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray, list[tuple[float, float, int]]]:
        """New ring, new scores and (score, smoothed, flag) of each row that has a full window."""
        w, w_a = self.cfg.w, self.cfg.w_a
        x = np.concatenate([ring, rows]) if len(ring) else rows
        _, win, y = T.windows(x, w)
        skip = max(0, len(win) - len(rows))
        out: list[tuple[float, float, int]] = []
        if len(win) > skip:
            pred = T.predict(win[skip:], self.params, self.cfg)
            top = ((np.abs(pred - y[skip:]) - self.med) / np.maximum(self.iqr, self.cfg.eps)).max(1)
            every = np.concatenate([scores, top])
            for k in range(len(scores), len(every)):
                s = every[max(0, k - w_a + 1) : k + 1].mean()
                out.append((float(every[k]), float(s), int(s > self.threshold)))
            scores = every[-(w_a - 1) :]
        return x[-w:], scores, out


def online_detector(vectors: DataFrame, detector: OnlineDetector) -> DataFrame:
    """(plant, tick, score, smooth, flag) from a stream of (plant, tick, x), in order of tick.

    State per plant is w vectors and w_a scores, whatever the length of the stream.
    """
    spark = vectors.sparkSession
    ship(spark)
    held = spark.sparkContext.broadcast(detector)
    n = detector.cfg.n

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        ring, scores = (np.array(v) for v in state.get) if state.exists else (np.empty(0), np.empty(0))
        ring = ring.reshape(-1, n)
        rows = pd.concat(list(frames)).sort_values("tick")
        ring, scores, out = held.value.run(ring, scores, np.stack(rows["x"].to_numpy()))
        state.update((ring.ravel().tolist(), scores.tolist()))
        ticks = rows["tick"].to_numpy()[len(rows) - len(out) :]
        yield pd.DataFrame([(key[0], int(t), *o) for t, o in zip(ticks, out, strict=True)], columns=["plant", "tick", "score", "smooth", "flag"])

    return vectors.groupBy("plant").applyInPandasWithState(step, "plant string, tick long, score double, smooth double, flag int", "ring array<double>, scores array<double>", "append", GroupStateTimeout.NoTimeout)
