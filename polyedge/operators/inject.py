"""Deterministic carrier and injected faults, by integer arithmetic that any engine repeats."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

KINDS = ("step", "ramp", "spike", "stuck", "noise", "gain", "phase", "flip", "swap", "dropout")
#: those that need no carrier
PLAIN = ("step", "ramp", "spike", "noise", "gain", "flip", "dropout")
SIZES = (0.05, 0.1, 0.2, 0.4)


def carrier(t: Column, i: Column) -> Column:
    """Sensor i's wave at tick t: its period by i mod 5, its lag by i div 5."""
    c, lag = F.pmod(i, F.lit(5)), F.floor(i / 5)
    return F.lit(0.5) + F.lit(0.35) * F.sin(F.lit(2 * math.pi) * (t - lag) / (F.lit(12) + c * 4))


def with_carrier(scaled: DataFrame) -> DataFrame:
    """Carrier plus a tenth of the scaled reading."""
    return scaled.withColumn("value", carrier(F.col("tick"), F.col("sensor_id")) + F.lit(0.1) * F.col("value"))


@dataclass(frozen=True)
class Fault:
    fault_id: int
    sensor_id: int
    t0: int
    t1: int
    kind: str
    size: float
    whole_group: bool


def schedule(ticks: int, n: int, start: int, count: int, shortest: int, longest: int, first: int = 0, kinds: tuple[str, ...] = KINDS) -> list[Fault]:
    """``count`` faults spread over ticks start .. ticks-1; where the longest would reach the next one, none
    takes more than half the way to it, so that each stays a fault of its own."""
    gap, out = (ticks - start) // (count + 1), []
    if count > 1 and longest >= gap:
        longest = max(1, gap // 2)
        shortest = min(shortest, longest)
    for q in range(count):
        t0 = start + ((q + 1) * (ticks - start)) // (count + 1)
        length = shortest + q % (longest - shortest + 1)
        k = q + first
        out.append(Fault(k, (7 * k + 3) % n, t0, min(ticks, t0 + length) - 1, kinds[k % len(kinds)], SIZES[(3 * k + k // 10) % 4], (k // 10) % 2 == 1))
    return out


def fault_rows(spark: SparkSession, faults: list[Fault]) -> DataFrame:
    rows = [(f.fault_id, f.sensor_id, f.t0, f.t1, f.kind, f.size, f.whole_group) for f in faults]
    return spark.createDataFrame(rows, "fault_id int, fault_sensor int, t0 long, t1 long, kind string, size double, whole_group boolean")


def apply_faults(p: DataFrame, faults: DataFrame, n: int) -> DataFrame:
    """Panel rows with the values that the faults leave (schedules are bounded and broadcast)."""
    t, i, v = F.col("tick"), F.col("sensor_id"), F.col("value")
    hit = (t >= F.col("t0")) & (t <= F.col("t1")) & ((i == F.col("fault_sensor")) | (F.col("whole_group") & (F.pmod(i, F.lit(5)) == F.pmod(F.col("fault_sensor"), F.lit(5)))))
    size, t0, t1 = F.col("size"), F.col("t0"), F.col("t1")
    noise = F.pmod(t * 7919 + i * 104729, F.lit(2003)) / 1001.0 - 1.0
    new = {
        "step": v + size,
        "ramp": v + size * (t - t0 + 1) / (t1 - t0 + 1),
        "spike": F.when(t == t0, v + 2 * size).otherwise(v),
        "stuck": carrier(t0, i),
        "noise": v + size * noise,
        "gain": v * (1 + 2 * size),
        "phase": carrier(t - 3, i),
        "flip": 1 - v,
        "swap": carrier(t, F.pmod(i + 1, F.lit(n))),
    }
    value = F.lit(0.0)
    for k, e in new.items():
        value = F.when(F.col("kind") == k, e).otherwise(value)
    value = F.when(F.col("kind").isNull(), v).otherwise(value)
    joined = p.join(F.broadcast(faults), hit, "left")
    cols = [c for c in p.columns if c != "value"]
    # overlapping faults on one reading: the one of the smallest id counts
    best = joined.select(*cols, value.alias("value"), F.col("fault_id")).groupBy(*cols).agg(F.min_by("value", F.coalesce("fault_id", F.lit(0))).alias("value"))
    return best.select(*p.columns)


def truth(spark: SparkSession, faults: list[Fault], ticks: int) -> DataFrame:
    """(tick, y): 1 inside any fault."""
    spans = fault_rows(spark, faults).select(F.explode(F.sequence("t0", "t1")).alias("tick")).distinct().withColumn("y", F.lit(1))
    return spark.range(ticks).select(F.col("id").alias("tick")).join(F.broadcast(spans), "tick", "left").withColumn("y", F.coalesce("y", F.lit(0)))
