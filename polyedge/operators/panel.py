"""Tall sensor panels from raw rows: regular ticks, gap completion, scaling and chronological splits.

A panel has tick (BIGINT from 0), ts (TIMESTAMP_NTZ), sensor_id (INT, dense in the order of the
sensor's name) and value (DOUBLE).
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from polyedge.sources import table

SECONDS = {"hour": 3600, "day": 86_400, "week": 604_800}


@dataclass(frozen=True)
class PanelSpec:
    """Where a panel comes from; expressions are plain SQL."""

    source: str
    ts: str
    unit: str
    key: str
    measures: dict[str, str]
    joins: tuple[tuple[str, str, str], ...] = ()
    stands_for: str = field(default="", compare=False)


PANELS = {
    "event_meter": PanelSpec("events", "ts", "hour", "event_type", {"count": "count(*)", "sum": "sum(cast(round(value * 100) as bigint))"}, stands_for="actuator and meter pair"),
    "user_cohort": PanelSpec("events", "ts", "hour", "lpad(cast(user_id % 50 as string), 2, '0')", {"": "sum(cast(round(value * 100) as bigint))"}, stands_for="55 channels"),
    "nation_ship": PanelSpec("lineitem", "l_shipdate", "week", "n_name", {"": "sum(cast(l_quantity as bigint))"}, (("supplier", "l_suppkey", "s_suppkey"), ("nation", "s_nationkey", "n_nationkey")), "25 channels"),
    "brand_status": PanelSpec("lineitem", "l_shipdate", "week", "p_brand || '|' || l_linestatus", {"": "sum(cast(l_quantity as bigint))"}, (("part", "l_partkey", "p_partkey"),), "51-sensor plant"),
    "nation_segment": PanelSpec("orders", "o_orderdate", "week", "n_name || '|' || c_mktsegment", {"": "count(*)"}, (("customer", "o_custkey", "c_custkey"), ("nation", "c_nationkey", "n_nationkey")), "123-sensor network"),
    "size_flow": PanelSpec("lineitem", "l_shipdate", "week", "lpad(cast(p_size as string), 2, '0')", {"": "sum(cast(l_quantity as bigint))"}, (("part", "l_partkey", "p_partkey"),), "52-variable simulator"),
    "flag_status": PanelSpec("lineitem", "l_shipdate", "day", "l_returnflag || l_linestatus", {"": "sum(cast(l_quantity as bigint))"}, stands_for="six nodes"),
}


def build_panel(df: DataFrame, ts: str, key: str, measures: dict[str, str], every: str) -> DataFrame:
    """(ts, sensor_name, value): one partial aggregation and one shuffle of groups."""
    stamp = F.date_trunc(every, F.col(ts)).cast("timestamp_ntz")
    got = df.groupBy(stamp.alias("ts"), F.expr(key).alias("__key")).agg(*[F.expr(e).cast("double").alias(f"m{i}") for i, e in enumerate(measures.values())])
    named = [F.struct(F.concat("__key", F.lit(f"|{n}" if n else "")).alias("name"), F.col(f"m{i}").alias("value")) for i, n in enumerate(measures)]
    return got.select("ts", F.explode(F.array(*named)).alias("x")).select("ts", F.col("x.name").alias("sensor_name"), F.col("x.value").alias("value"))


def densify(rows: DataFrame, every: str, fill: str = "zero", train: float = 0.6) -> DataFrame:
    """Every sensor at every tick.  ``fill``: ``zero``, ``ffill`` (then back-fill, then zero) or ``median``
    (the last value forward; what precedes the first gets the median of the sensor's readings in the
    first ``train`` of the ticks, zero if there is none).

    The grid is the cross of the sensor list (bounded by the schema) with the tick range, which is
    generated by ``sequence`` and so never read or shuffled as data.
    """
    step = f"INTERVAL 1 {every.upper()}"
    span = rows.agg(F.min("ts").alias("lo"), F.max("ts").alias("hi"))
    ticks = span.where("lo IS NOT NULL").select(F.posexplode(F.expr(f"sequence(lo, hi, {step})")).alias("tick", "ts")).select(F.col("tick").cast("bigint").alias("tick"), "ts")
    sensors = rows.select("sensor_name").distinct().withColumn("sensor_id", (F.row_number().over(Window.orderBy("sensor_name")) - 1).cast("int"))
    grid = ticks.crossJoin(F.broadcast(sensors))
    full = grid.join(rows, ["ts", "sensor_name"], "left")
    if fill == "zero":
        value = F.coalesce("value", F.lit(0.0))
    elif fill == "ffill":
        w = Window.partitionBy("sensor_id").orderBy("tick")
        value = F.coalesce(F.last("value", True).over(w), F.first("value", True).over(w.rowsBetween(0, Window.unboundedFollowing)), F.lit(0.0))
    elif fill == "median":
        part = full.crossJoin(ticks.agg(F.floor((F.max("tick") + 1) * train).alias("__until"))).where("tick < __until")
        middle = part.groupBy("sensor_id").agg(F.percentile("value", 0.5).alias("__middle"))
        full = full.join(middle, "sensor_id", "left")
        value = F.coalesce(F.last("value", True).over(Window.partitionBy("sensor_id").orderBy("tick")), "__middle", F.lit(0.0))
    else:
        raise ValueError("fill is zero, ffill or median")
    return full.select("tick", "ts", "sensor_id", value.alias("value"))


def panel(spark: SparkSession, sf_dir: str, name: str, every: str | None = None) -> DataFrame:
    """A named panel of the given tables, zero-filled."""
    if name == "axis":
        return axis_panel(spark, sf_dir)
    s = PANELS[name]
    df = table(spark, sf_dir, s.source)
    for other, left, right in s.joins:
        dim = table(spark, sf_dir, other)
        df = df.join(dim, df[left] == dim[right])
    return densify(build_panel(df, s.ts, s.key, s.measures, every or s.unit), every or s.unit)


def axis_panel(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Embedding axes as sensors, vector ids as ticks of one second."""
    e = table(spark, sf_dir, "embeddings", ["vec_id", "embedding"])
    low = e.agg(F.min("vec_id").alias("low"))
    rows = e.crossJoin(F.broadcast(low)).select((F.col("vec_id") - F.col("low")).alias("tick"), F.posexplode("embedding").alias("sensor_id", "value"))
    return rows.select("tick", F.timestamp_seconds(F.lit(0) + F.col("tick")).cast("timestamp_ntz").alias("ts"), "sensor_id", F.col("value").cast("double").alias("value"))


def with_split(p: DataFrame, train: float = 0.6, validation: float = 0.2) -> DataFrame:
    """Chronological parts: ``train``, ``validation`` and ``test`` by tick bounds."""
    n = p.agg((F.max("tick") + 1).alias("n"))
    a, b = F.floor(F.col("n") * train), F.floor(F.col("n") * (train + validation))
    part = F.when(F.col("tick") < a, "train").when(F.col("tick") < b, "validation").otherwise("test")
    return p.crossJoin(F.broadcast(n)).withColumn("split", part).drop("n")


def fit_minmax(p: DataFrame) -> DataFrame:
    """Bounds per sensor from the training rows (all rows if there is no split)."""
    rows = p.where("split = 'train'") if "split" in p.columns else p
    return rows.groupBy("sensor_id").agg(F.min("value").alias("lo"), F.max("value").alias("hi"))


def apply_minmax(p: DataFrame, bounds: DataFrame, clip: bool = False) -> DataFrame:
    """To [0, 1] of the training range; a constant sensor becomes 0."""
    x = F.when(F.col("hi") > F.col("lo"), (F.col("value") - F.col("lo")) / (F.col("hi") - F.col("lo"))).otherwise(F.lit(0.0))
    if clip:
        x = F.least(F.greatest(x, F.lit(0.0)), F.lit(1.0))
    return p.join(F.broadcast(bounds), "sensor_id", "left").withColumn("value", x).drop("lo", "hi")


def attach_truth(p: DataFrame, truth: DataFrame) -> DataFrame:
    """Panel rows with the label of their tick (0 where none is known)."""
    return p.join(truth, "tick", "left").withColumn("y", F.coalesce("y", F.lit(0)))


def to_wide(p: DataFrame, sensors: list[int]) -> DataFrame:
    """One row per tick, a column per sensor of a fixed list."""
    wide = p.groupBy("tick").pivot("sensor_id", sensors).agg(F.first("value"))
    return wide.select("tick", *[F.col(f"`{s}`").alias(f"s{s}") for s in sensors])


def to_tall(wide: DataFrame) -> DataFrame:
    cols = [c for c in wide.columns if c != "tick"]
    tall = wide.unpivot(["tick"], cols, "sensor", "value")
    return tall.select("tick", F.substring("sensor", 2, 9).cast("int").alias("sensor_id"), "value")


def to_vectors(p: DataFrame, value: str = "value") -> DataFrame:
    """One row per tick with the readings of all sensors in order: the block layout."""
    kept = [c for c in ("split", "ts") if c in p.columns]
    rows = p.groupBy("tick", *kept).agg(F.sort_array(F.collect_list(F.struct("sensor_id", F.col(value).alias("v")))).alias("x"))
    return rows.select("tick", *kept, F.transform("x", lambda s: s["v"]).alias("x"))
