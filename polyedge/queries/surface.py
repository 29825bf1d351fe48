"""Functions at the SQL surface as queries: inline functions, UDAF, UDTF and the custom source."""

from __future__ import annotations

from pyspark.sql import functions as F

from polyedge.functions import algebra, udf
from polyedge.operators import panel as P, relational as R
from polyedge.queries.methods import LEARNED_SQL, learned_six, trace_sql
from polyedge.queries.panels import SCALED_SQL, panel_sql, scaled
from polyedge.session import configure, ship
from polyedge.sources import simulated, table


def q_inline_functions(spark, d):
    algebra.install(spark)
    e = table(configure(spark), d, "embeddings", ["vec_id", "embedding"]).select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("z"))
    return e.select("vec_id", F.expr("round(vec_dot(z, z), 4)").alias("sq"), F.expr("round(vec_l2(vec_scale(z, 2D)), 4)").alias("twice"))


def q_udaf_iqr(spark, d):
    ship(spark)
    return table(configure(spark), d, "events").groupBy("event_type").agg(F.round(udf.robust_iqr("value"), 6).alias("iqr"))


def q_udtf_windows(spark, d):
    ship(spark)
    spark.udtf.register("lag_windows", udf.LagWindows)
    P.panel(configure(spark), d, "flag_status").select("sensor_id", "tick", "value").createOrReplaceTempView("sensor_rows")
    return spark.sql("SELECT sensor_id, tick, j, x FROM lag_windows(TABLE(sensor_rows) PARTITION BY sensor_id ORDER BY tick)")


def q_udaf_vector_sum(spark, d):
    ship(spark)
    e = table(configure(spark), d, "embeddings", ["label", "embedding"]).select("label", F.col("embedding").cast("array<double>").alias("z"))
    return e.groupBy("label").agg(udf.vector_sum("z").alias("z")).select("label", F.posexplode("z").alias("place", "total")).withColumn("total", F.round("total", 4))


def q_udtf_khop(spark, d):
    """Every node as a root, three hops, a root to a partition."""
    ship(spark)
    spark.udtf.register("khop", udf.KHop)
    members = learned_six(spark, d)
    members.crossJoin(members.select(F.col("sensor_id").alias("root")).distinct()).createOrReplaceTempView("rooted_members")
    return spark.sql("SELECT root, hop, to_id FROM khop(TABLE(rooted_members) PARTITION BY (root), 3)")


def q_cogroup_drift(spark, d):
    """How far each sensor's test readings have moved from its training readings."""
    ship(spark)
    p = scaled(spark, d, "nation_ship")
    moved = R.drift(p.where("split = 'train'"), p.where("split = 'test'"), "sensor_id", "value")
    return moved.withColumn("distance", F.round("distance", 6))


def q_simulated_source(spark, d):
    """Simulated sensors beside the meters of the events, tick by tick."""
    ship(spark)
    simulated.register(spark)
    s = spark.read.format("simulated_sensors").option("ticks", 600).option("sensors", 7).option("fault", "3:100:120").load()
    held = P.panel(configure(spark), d, "event_meter").select("tick", "sensor_id", F.col("value").alias("held"))
    return s.join(held, ["tick", "sensor_id"]).groupBy("sensor_id").agg(F.count("*").alias("n"), F.round(F.sum("value"), 6).alias("total"), F.sum("held").alias("held"))


QUERIES = {k: v for k, v in globals().items() if k.startswith("q_")}
ORACLES = {
    "q_inline_functions": "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 4) AS sq, round(2 * sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE)))), 4) AS twice FROM embeddings",
    "q_udaf_iqr": "SELECT event_type, round(quantile_cont(value, 0.75) - quantile_cont(value, 0.25), 6) AS iqr FROM events GROUP BY 1",
    "q_udtf_windows": f"WITH {panel_sql('flag_status')} SELECT t.sensor_id, t.tick, CAST(j.j AS INTEGER) AS j, x.value AS x FROM pg t CROSS JOIN (SELECT unnest(range(0, 5)) AS j) j JOIN pg x ON x.sensor_id = t.sensor_id AND x.tick = t.tick - 5 + j.j WHERE t.tick >= 5",
    "q_udaf_vector_sum": "WITH f AS (SELECT label, generate_subscripts(embedding, 1) - 1 AS place, CAST(unnest(embedding) AS DOUBLE) AS v FROM embeddings) SELECT label, CAST(place AS INTEGER) AS place, round(sum(v), 4) AS total FROM f GROUP BY 1, 2",
    "q_udtf_khop": trace_sql(f"{panel_sql('flag_status')}, {LEARNED_SQL}", "six", "0, 1, 2, 3, 4, 5", 3),
    "q_cogroup_drift": f"WITH {panel_sql('nation_ship')}, {SCALED_SQL}, "
    "n AS (SELECT sensor_id, count(*) FILTER (split = 'train') AS a, count(*) FILTER (split = 'test') AS b FROM sc GROUP BY 1), "
    "c AS (SELECT sensor_id, count(*) FILTER (split = 'train') OVER w AS below_a, count(*) FILTER (split = 'test') OVER w AS below_b FROM sc WHERE split <> 'validation' WINDOW w AS (PARTITION BY sensor_id ORDER BY value RANGE UNBOUNDED PRECEDING)) "
    "SELECT sensor_id, round(max(abs(below_a / a::DOUBLE - below_b / b::DOUBLE)), 6) AS distance, any_value(a) AS before, any_value(b) AS after FROM c JOIN n USING (sensor_id) GROUP BY 1",
    "q_simulated_source": f"WITH {panel_sql('event_meter')}, v AS (SELECT i, t, 0.5::DOUBLE + 0.35::DOUBLE * sin(2 * pi() * (t - i // 5) / (12 + 4 * (i % 5))) AS v FROM (SELECT unnest(range(0, 600)) AS t) CROSS JOIN (SELECT unnest(range(0, 7)) AS i)) SELECT CAST(i AS INTEGER) AS sensor_id, count(*) AS n, round(sum(CASE WHEN i = 3 AND t BETWEEN 100 AND 120 THEN 1 - v ELSE v END), 6) AS total, sum(value) AS held FROM v JOIN pg ON tick = t AND sensor_id = i GROUP BY 1",
}
