"""Comparison detectors as Spark plans; those on neighbours with exact SQL, those on eigenvectors and regressions without."""

from __future__ import annotations

from polyedge.baselines import distributed as B
from polyedge.operators import panel as P
from polyedge.queries.panels import SCALED_SQL, panel_sql, scaled

PANEL, SENSORS, ROUNDS, K = "flag_status", 6, 3, 10


def vectors(spark, d):
    return P.to_vectors(scaled(spark, d, PANEL)).select("tick", "split", "x")


def q_knn_score(spark, d):
    return B.to_rows(B.knn_score(vectors(spark, d), 5))


def q_lof(spark, d):
    return B.to_rows(B.lof(vectors(spark, d), K))


def q_bagging(spark, d):
    return B.to_rows(B.bagging(vectors(spark, d), SENSORS, ROUNDS, K))


def q_pca_resid(spark, d):
    return B.to_rows(B.pca_residual(vectors(spark, d)), ("tick", "sensor_id", "dev"))


def q_var1(spark, d):
    return B.to_rows(B.var_residual(vectors(spark, d), 1), ("tick", "sensor_id", "dev"))


def near_sql(p: str, k: int, sensors: list[int] | None = None) -> str:
    """CTEs vec, near: the k nearest training ticks of training and test ticks."""
    on = f" AND sensor_id IN ({', '.join(map(str, sensors))})" if sensors else ""
    return (
        f"vec{p} AS (SELECT tick, split, list(value ORDER BY sensor_id) AS x FROM sc WHERE split <> 'validation'{on} GROUP BY ALL), "
        f"near{p} AS (SELECT q.tick AS q, q.split, j.tick AS j, round(list_distance(q.x, j.x), {B.DIGITS}) AS dist FROM vec{p} q JOIN vec{p} j ON j.split = 'train' AND j.tick <> q.tick "
        f"QUALIFY row_number() OVER (PARTITION BY q ORDER BY dist, j) <= {k})"
    )


def lof_sql(p: str, k: int, sensors: list[int] | None = None) -> str:
    return (
        near_sql(p, k, sensors)
        + f", reach{p} AS (SELECT q AS j, max(dist) AS reach FROM near{p} GROUP BY 1), "
        f"dens{p} AS (SELECT q, 1 / greatest(avg(greatest(dist, reach)), 0.000000000001::DOUBLE) AS density FROM near{p} JOIN reach{p} USING (j) GROUP BY 1), "
        f"lof{p} AS (SELECT n.q AS tick, avg(t.density) / any_value(o.density) AS score FROM near{p} n JOIN dens{p} t ON t.q = n.j JOIN dens{p} o ON o.q = n.q WHERE n.split = 'test' GROUP BY 1)"
    )


BASE = f"WITH {panel_sql(PANEL)}, {SCALED_SQL}, "
QUERIES = {k: v for k, v in globals().items() if k.startswith("q_")}
ORACLES = {
    "q_knn_score": BASE + near_sql("", 5) + " SELECT q AS tick, round(max(dist), 5) AS score FROM near WHERE split = 'test' GROUP BY 1",
    "q_lof": BASE + lof_sql("", K) + " SELECT tick, round(score, 5) AS score FROM lof",
    "q_bagging": BASE + ", ".join(lof_sql(str(i), K, s) for i, s in enumerate(B.subsets(SENSORS, ROUNDS))) + " SELECT tick, round(sum(score), 5) AS score FROM (" + " UNION ALL ".join(f"SELECT * FROM lof{i}" for i in range(ROUNDS)) + ") GROUP BY 1",
}
