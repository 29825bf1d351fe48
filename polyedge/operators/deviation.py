"""Deviation scorer: robust per-sensor scores of forecast errors, smoothed and held against a threshold."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

#: ticks of a range that one task smooths
CHUNK = 10_000


def abs_error(forecast: DataFrame) -> DataFrame:
    return forecast.withColumn("dev", F.abs(F.col("y") - F.col("y_hat")))


def fit_robust(dev: DataFrame, on: str = "validation", exact: bool = True, accuracy: int = 10_000) -> DataFrame:
    """Median and interquartile range of each sensor's error over one split (``self``: over all rows)."""
    rows = dev if on == "self" else dev.where(F.col("split") == on)
    if exact:
        q = [F.percentile("dev", x) for x in (0.25, 0.5, 0.75)]
    else:
        q = [F.percentile_approx("dev", x, accuracy) for x in (0.25, 0.5, 0.75)]
    return rows.groupBy("sensor_id").agg(q[1].alias("med"), (q[2] - q[0]).alias("iqr"))


def robust_score(dev: DataFrame, stats: DataFrame, eps: float = 1e-6) -> DataFrame:
    return dev.join(stats, "sensor_id").withColumn("score", (F.col("dev") - F.col("med")) / F.greatest(F.col("iqr"), F.lit(eps)))


def tick_max(score: DataFrame) -> DataFrame:
    """Greatest score of each tick and its sensor (ties: the smallest id)."""
    best = F.max(F.struct("score", (-F.col("sensor_id")).alias("neg")))
    kept = [c for c in ("split",) if c in score.columns]
    return score.groupBy("tick", *kept).agg(best.alias("b")).select("tick", *kept, F.col("b.score").alias("raw"), (-F.col("b.neg")).alias("top_sensor"))


def smooth(ticks: DataFrame, w_a: int = 10, mode: str = "trailing", chunk: int | None = CHUNK) -> DataFrame:
    """Moving average over ticks.  ``trailing``: the last w_a; ``printed``: w_a + 2 ticks over w_a.

    The ticks are dealt to ranges of ``chunk`` with a halo, so no single task sees all of them;
    with None one window runs over all.
    """
    back = w_a - 1 if mode == "trailing" else w_a + 1
    if chunk:
        own = F.floor(F.col("tick") / chunk)
        rows = ticks.withColumn("__c", F.explode(F.sequence(own, F.floor((F.col("tick") + back) / chunk))))
        w = Window.partitionBy("__c").orderBy("tick").rowsBetween(-back, 0)
    else:
        rows, w = ticks, Window.orderBy("tick").rowsBetween(-back, 0)
    value = F.avg("raw").over(w) if mode == "trailing" else F.sum("raw").over(w) / F.lit(float(w_a))
    out = rows.withColumn("smooth", value)
    return out.where(F.col("__c") == F.floor(F.col("tick") / chunk)).drop("__c") if chunk else out


def fit_threshold(smoothed: DataFrame) -> float | None:
    return smoothed.where("split = 'validation'").agg(F.max("smooth")).first()[0]


def flag(smoothed: DataFrame, threshold: float) -> DataFrame:
    """Test ticks, flagged where strictly above the threshold."""
    return smoothed.where("split = 'test'").select("tick", "smooth", F.lit(threshold).alias("threshold"), (F.col("smooth") > threshold).cast("int").alias("flag"))


def rank_sensors(score: DataFrame, top: int) -> DataFrame:
    w = Window.partitionBy("tick").orderBy(F.desc("score"), "sensor_id")
    return score.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= top)


def persistence(p: DataFrame, chunk: int | None = None) -> DataFrame:
    """Forecast by the last reading."""
    from polyedge.operators.windows import lagged

    got = lagged(p, 1, chunk)
    kept = [c for c in ("split",) if c in got.columns]
    return got.select("tick", *kept, "sensor_id", F.col("target").alias("y"), F.col("win")[0].alias("y_hat"))


def detect(forecast: DataFrame, w_a: int = 10, mode: str = "trailing", on: str = "validation", eps: float = 1e-6, exact: bool = True, chunk: int | None = CHUNK) -> tuple[DataFrame, DataFrame, float]:
    """Scores per node, smoothed ticks and the threshold of a split forecast."""
    dev = abs_error(forecast)
    score = robust_score(dev, fit_robust(dev, on, exact), eps)
    ticks = smooth(tick_max(score), w_a, mode, chunk)
    return score, ticks, fit_threshold(ticks)
