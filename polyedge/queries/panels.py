"""Panels, scaling, splits and windows, with their SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from polyedge.operators import panel as P, windows as W
from polyedge.session import configure

WIDTH = 5


def panel_sql(name: str) -> str:
    """CTEs ``rows``, ``sensors``, ``ticks``, ``pg`` (tick, ts, sensor_id, value) for DuckDB."""
    if name == "axis":
        return "pg AS (SELECT vec_id - (SELECT min(vec_id) FROM embeddings) AS tick, make_timestamp(CAST((vec_id - (SELECT min(vec_id) FROM embeddings)) * 1000000 AS BIGINT)) AS ts, CAST(generate_subscripts(embedding, 1) - 1 AS INTEGER) AS sensor_id, CAST(unnest(embedding) AS DOUBLE) AS value FROM embeddings)"
    s = P.PANELS[name]
    tables = s.source + "".join(f" JOIN {t} ON {a} = {b}" for t, a, b in s.joins)
    parts = [f"SELECT date_trunc('{s.unit}', {s.ts}) AS ts, {s.key} || '{'|' + n if n else ''}' AS name, CAST({e} AS DOUBLE) AS value FROM {tables} GROUP BY 1, {s.key}" for n, e in s.measures.items()]
    return (
        f"rows AS ({' UNION ALL '.join(parts)}), "
        "sensors AS (SELECT name, CAST(row_number() OVER (ORDER BY name) - 1 AS INTEGER) AS sensor_id FROM (SELECT DISTINCT name FROM rows)), "
        f"ticks AS (SELECT ts, row_number() OVER (ORDER BY ts) - 1 AS tick FROM (SELECT unnest(generate_series(min(ts), max(ts), INTERVAL 1 {s.unit})) AS ts FROM rows)), "
        "pg AS (SELECT t.tick, CAST(t.ts AS TIMESTAMP) AS ts, s.sensor_id, coalesce(r.value, 0.0) AS value FROM ticks t CROSS JOIN sensors s LEFT JOIN rows r ON r.ts = t.ts AND r.name = s.name)"
    )


SPLIT_SQL = "CASE WHEN tick < floor((SELECT max(tick) + 1 FROM pg) * 0.6) THEN 'train' WHEN tick < floor((SELECT max(tick) + 1 FROM pg) * 0.8) THEN 'validation' ELSE 'test' END"
SCALED_SQL = f"sp AS (SELECT *, {SPLIT_SQL} AS split FROM pg), mm AS (SELECT sensor_id, min(value) AS lo, max(value) AS hi FROM sp WHERE split = 'train' GROUP BY 1), sc AS (SELECT sp.tick, sp.ts, sp.sensor_id, sp.split, CASE WHEN hi > lo THEN (value - lo) / (hi - lo) ELSE 0.0 END AS value FROM sp JOIN mm USING (sensor_id))"

SPARSE_SQL = "f AS (SELECT t.tick, s.sensor_id, r.value FROM ticks t CROSS JOIN sensors s LEFT JOIN rows r ON r.ts = t.ts AND r.name = s.name)"


def _panel(name):
    return lambda spark, d: P.panel(configure(spark), d, name)


def scaled(spark, d, name):
    p = P.with_split(P.panel(configure(spark), d, name))
    return P.apply_minmax(p, P.fit_minmax(p))


def q_minmax(spark, d):
    return scaled(spark, d, "nation_ship").select("tick", "sensor_id", F.round("value", 6).alias("value"))


def q_split(spark, d):
    p = P.with_split(P.panel(configure(spark), d, "nation_ship"))
    return p.groupBy("split").agg(F.min("tick").alias("lo"), F.max("tick").alias("hi"), F.count("*").alias("n"))


def q_windows(spark, d):
    got = W.lagged(P.panel(configure(spark), d, "flag_status"), WIDTH, chunk=500)
    return got.select("tick", "sensor_id", "target", F.posexplode("win").alias("j", "x"))


def q_pivot(spark, d):
    return P.to_wide(P.panel(configure(spark), d, "flag_status"), list(range(6)))


def q_unpivot(spark, d):
    return P.to_tall(P.to_wide(P.panel(configure(spark), d, "flag_status"), list(range(6))))


def _filled(spark, d, fill):
    s = P.PANELS["user_cohort"]
    rows = P.build_panel(P.table(configure(spark), d, "events"), s.ts, s.key, s.measures, s.unit)
    return P.densify(rows, s.unit, fill).select("tick", "sensor_id", "value")


def q_ffill(spark, d):
    return _filled(spark, d, "ffill")


def q_median_fill(spark, d):
    return _filled(spark, d, "median")


QUERIES = {f"q_panel_{n}": _panel(n) for n in [*P.PANELS, "axis"]} | {"q_minmax": q_minmax, "q_split": q_split, "q_windows": q_windows, "q_pivot": q_pivot, "q_unpivot": q_unpivot, "q_ffill": q_ffill, "q_median_fill": q_median_fill}
ORACLES = {f"q_panel_{n}": f"WITH {panel_sql(n)} SELECT tick, ts, sensor_id, value FROM pg" for n in [*P.PANELS, "axis"]} | {
    "q_minmax": f"WITH {panel_sql('nation_ship')}, {SCALED_SQL} SELECT tick, sensor_id, round(value, 6) AS value FROM sc",
    "q_split": f"WITH {panel_sql('nation_ship')}, {SCALED_SQL} SELECT split, min(tick) AS lo, max(tick) AS hi, count(*) AS n FROM sp GROUP BY 1",
    "q_windows": f"WITH {panel_sql('flag_status')} SELECT t.tick, t.sensor_id, t.value AS target, CAST(j.j AS INTEGER) AS j, x.value AS x FROM pg t CROSS JOIN (SELECT unnest(range(0, {WIDTH})) AS j) j JOIN pg x ON x.sensor_id = t.sensor_id AND x.tick = t.tick - {WIDTH} + j.j WHERE t.tick >= {WIDTH}",
    "q_pivot": f"WITH {panel_sql('flag_status')} SELECT tick, " + ", ".join(f"max(CASE WHEN sensor_id = {i} THEN value END) AS s{i}" for i in range(6)) + " FROM pg GROUP BY tick",
    "q_unpivot": f"WITH {panel_sql('flag_status')} SELECT tick, sensor_id, value FROM pg",
    "q_median_fill": f"WITH {panel_sql('user_cohort')}, {SPARSE_SQL}, "
    "m AS (SELECT sensor_id, quantile_cont(value, 0.5) AS middle FROM f WHERE tick < floor((SELECT max(tick) + 1 FROM f) * 0.6) GROUP BY 1) "
    "SELECT tick, sensor_id, coalesce(last_value(value IGNORE NULLS) OVER (PARTITION BY sensor_id ORDER BY tick), middle, 0.0) AS value FROM f JOIN m USING (sensor_id)",
    "q_ffill": f"WITH {panel_sql('user_cohort')}, {SPARSE_SQL}, "
    "g AS (SELECT tick, sensor_id, last_value(value IGNORE NULLS) OVER (PARTITION BY sensor_id ORDER BY tick) AS a, first_value(value IGNORE NULLS) OVER (PARTITION BY sensor_id ORDER BY tick ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS b FROM f) "
    "SELECT tick, sensor_id, coalesce(a, b, 0.0) AS value FROM g",
}
