"""Sliding windows that end before their target, batches, and chunks with a halo."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F


def lagged(p: DataFrame, w: int, chunk: int | None = None) -> DataFrame:
    """(tick, sensor_id, win, target): the w readings before each tick.

    Without ``chunk`` the window runs per sensor, so a job has as many tasks as sensors.  With it,
    each sensor's ticks are cut into chunks that also receive the w ticks before them: the same
    rows, with parallelism that grows with the number of ticks.
    """
    if chunk is None:
        spec, rows = Window.partitionBy("sensor_id").orderBy("tick"), p.withColumn("__own", F.lit(True))
    else:
        rows = with_halo(p, w, chunk)
        spec = Window.partitionBy("sensor_id", "__chunk").orderBy("tick")
    win = F.collect_list("value").over(spec.rowsBetween(-w, -1))
    kept = [c for c in ("ts", "split") if c in p.columns]
    out = rows.withColumn("win", win).where((F.size("win") == w) & F.col("__own"))
    return out.select("tick", *kept, "sensor_id", "win", F.col("value").alias("target"))


def with_halo(p: DataFrame, w: int, chunk: int) -> DataFrame:
    """Rows dealt to their chunk, and once more to the chunks whose windows reach back to them."""
    own = F.floor(F.col("tick") / chunk).cast("bigint")
    last = F.floor((F.col("tick") + w) / chunk).cast("bigint")
    dealt = p.withColumn("__chunk", F.explode(F.sequence(own, last)))
    return dealt.withColumn("__own", F.col("__chunk") == F.floor(F.col("tick") / chunk))


def batches(ticks: DataFrame, size: int, seed: int, epoch: int) -> DataFrame:
    """Batch numbers for one epoch: ticks in the order of a seeded hash, cut by size."""
    order = Window.orderBy(F.xxhash64("tick", F.lit(seed), F.lit(epoch)), "tick")
    return ticks.select("tick").distinct().withColumn("batch", F.floor((F.row_number().over(order) - 1) / size).cast("bigint"))
