"""Accuracy measures over flags and truth."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F


def confusion(rows: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """tp, fp, fn, tn of (y, flag) rows."""
    def n(y: int, f: int):
        return F.coalesce(F.sum(F.when((F.col("y") == y) & (F.col("flag") == f), 1).otherwise(0)), F.lit(0)).cast("bigint")

    return rows.groupBy(*(keys or [])).agg(n(1, 1).alias("tp"), n(0, 1).alias("fp"), n(1, 0).alias("fn"), n(0, 0).alias("tn"))


def prf(counts: DataFrame) -> DataFrame:
    """Precision, recall and F1 in percent, 0 where undefined."""
    p = F.when(F.col("tp") + F.col("fp") > 0, 100.0 * F.col("tp") / (F.col("tp") + F.col("fp"))).otherwise(0.0)
    r = F.when(F.col("tp") + F.col("fn") > 0, 100.0 * F.col("tp") / (F.col("tp") + F.col("fn"))).otherwise(0.0)
    f = F.when(2 * F.col("tp") + F.col("fp") + F.col("fn") > 0, 200.0 * F.col("tp") / (2 * F.col("tp") + F.col("fp") + F.col("fn"))).otherwise(0.0)
    return counts.select("*", p.alias("precision"), r.alias("recall"), f.alias("f1"))


def adjust_segments(rows: DataFrame, by: list[str] | None = None, chunk: int = 100_000) -> DataFrame:
    """A flag anywhere in a contiguous true segment flags all of it (rows: tick, y, flag).

    Segments are numbered inside ranges of ``chunk`` ticks; one row a range then tells which of them go
    on over a border, so no task sees more ticks than a range has.
    """
    keys = by or []
    w = Window.partitionBy(*keys, "__c").orderBy("tick")
    begins = ((F.col("y") == 1) & (F.coalesce(F.lag("y").over(w), F.lit(0)) == 0)).cast("int")
    marked = rows.withColumn("__c", F.floor(F.col("tick") / chunk)).withColumn("__b", begins).withColumn("__seg", F.sum("__b").over(w))
    along = Window.partitionBy(*keys).orderBy("__c")
    ends = marked.groupBy(*keys, "__c").agg(F.min_by("y", "tick").alias("__first"), F.max_by("y", "tick").alias("__last"), F.max("__seg").alias("__segs"))
    ends = ends.withColumn("__joined", (F.col("__first") == 1) & (F.coalesce(F.lag("__last").over(along), F.lit(0)) == 1))
    # the group of a range's last segment; the first one, if joined, is of the group before
    ends = ends.withColumn("__g", F.sum(F.when(F.col("__joined") & (F.col("__segs") == 1), 0).otherwise(1)).over(along))
    ends = ends.withColumn("__before", F.lag("__g").over(along))
    seg = Window.partitionBy(*keys, "__c", "__seg", "y")
    held = marked.withColumn("__hit", F.max("flag").over(seg)).join(ends, [*keys, "__c"])
    group = F.when((F.col("__seg") == 1) & F.col("__joined"), F.col("__before")).when((F.col("__seg") == F.col("__segs")) & (F.col("__last") == 1), F.col("__g"))
    held = held.withColumn("__group", F.when(F.col("y") == 1, group))
    crossing = held.where("__group IS NOT NULL").groupBy(*keys, "__group").agg(F.max("__hit").alias("__any"))
    out = held.join(crossing, [*keys, "__group"], "left")
    flag = F.when(F.col("y") == 1, F.coalesce("__any", "__hit")).otherwise(F.col("flag"))
    return out.select(*[flag.alias(c) if c == "flag" else c for c in rows.columns])


def fault_rate(rows: DataFrame) -> DataFrame:
    """Detected share of each fault's ticks in percent (rows: fault_id, flag on faulty ticks)."""
    return rows.groupBy("fault_id").agg((100.0 * F.sum("flag") / F.count("*")).alias("fdr"))


def false_alarm(rows: DataFrame) -> DataFrame:
    return rows.where("y = 0").agg((100.0 * F.avg("flag")).alias("false_alarm"))


def mean_runs(runs: DataFrame, keys: list[str], cols: list[str]) -> DataFrame:
    return runs.groupBy(*keys).agg(*[F.avg(c).alias(c) for c in cols], *[F.stddev(c).alias(f"sd_{c}") for c in cols])


def relative_gain(df: DataFrame, ours: str, other: str, name: str = "gain") -> DataFrame:
    """Gain in percent of our value, as the published comparisons compute it."""
    return df.withColumn(name, F.when(F.col(ours) != 0, 100.0 * (F.col(ours) - F.col(other)) / F.col(ours)))


def leaderboard(df: DataFrame, by: list[str], value: str) -> DataFrame:
    return df.withColumn("place", F.dense_rank().over(Window.partitionBy(*by).orderBy(F.desc(value)))).withColumn("best", F.col("place") == 1).withColumn("second", F.col("place") == 2)


def forecast_error(f: DataFrame, keys: list[str]) -> DataFrame:
    e = F.col("y") - F.col("y_hat")
    return f.groupBy(*keys).agg(F.avg(e * e).alias("mse"), F.avg(F.abs(e)).alias("mae"), F.sqrt(F.avg(e * e)).alias("rmse"))


def cross_entropy(rows: DataFrame, clip: float = 1e-7) -> DataFrame:
    p = F.least(F.greatest(F.col("p"), F.lit(clip)), F.lit(1 - clip))
    return rows.agg(F.avg(-F.col("y") * F.log(p) - (1 - F.col("y")) * F.log(1 - p)).alias("bce"))
