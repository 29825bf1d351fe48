"""Python functions at the SQL surface: Arrow-batched scoring, grouped aggregates and table functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf


@pandas_udf(T.DoubleType())
def robust_iqr(v: pd.Series) -> float:
    """Interquartile range (grouped aggregate; no partial aggregation, so for bounded groups)."""
    q = np.percentile(v.dropna(), [25, 75]) if v.notna().any() else (np.nan, np.nan)
    return float(q[1] - q[0])


@pandas_udf(T.ArrayType(T.DoubleType()))
def vector_sum(v: pd.Series) -> list:
    """Sum of the vectors of a group, place by place; null vectors add nothing (grouped aggregate, for bounded groups)."""
    rows = [np.asarray(x, np.float64) for x in v if x is not None]
    return np.sum(rows, axis=0).tolist() if rows else None


def score_windows(params: dict, cfg):
    """Iterator UDF from a flattened window [n*w] to the forecast [n]; weights load once a task."""
    from polyedge.models.train import predict

    @pandas_udf(T.ArrayType(T.DoubleType()))
    def f(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for s in batches:
            win = np.stack(s.to_numpy()).reshape(-1, cfg.n, cfg.w)
            yield pd.Series(list(predict(win, params, cfg)))

    return f


@udtf(returnType=T.StructType([T.StructField("sensor_id", T.IntegerType()), T.StructField("tick", T.LongType()), T.StructField("j", T.IntegerType()), T.StructField("x", T.DoubleType())]))
class LagWindows:
    """Rows of one sensor, ordered by tick, to the (sensor_id, tick, j, x) of their windows of five."""

    WIDTH = 5

    def __init__(self):
        self.ring: list[float] = []

    def eval(self, row):
        if len(self.ring) == self.WIDTH:
            for j, x in enumerate(self.ring):
                yield row["sensor_id"], row["tick"], j, x
        self.ring = [*self.ring[-(self.WIDTH - 1) :], row["value"]]


@udtf(returnType=T.StructType([T.StructField("root", T.IntegerType()), T.StructField("hop", T.IntegerType()), T.StructField("to_id", T.IntegerType())]))
class KHop:
    """Nodes within ``hops`` of a root, from the rows (root, edge_id, sensor_id) of one root.

    A task holds the memberships, which the sensor list bounds, and walks them for one root.
    """

    def __init__(self):
        self.root, self.hops = None, 0
        self.members: dict[int, set[int]] = {}
        self.edges: dict[int, set[int]] = {}

    def eval(self, row, hops: int):
        self.root, self.hops = row["root"], hops
        self.members.setdefault(row["edge_id"], set()).add(row["sensor_id"])
        self.edges.setdefault(row["sensor_id"], set()).add(row["edge_id"])

    def terminate(self):
        seen, front = {self.root}, {self.root}
        for hop in range(1, self.hops + 1):
            front = {m for s in front for e in self.edges.get(s, ()) for m in self.members[e]} - seen
            seen |= front
            for s in sorted(front):
                yield self.root, hop, s


def install(spark: SparkSession, sf_dir: str | None = None) -> None:
    """Register the functions and, with a directory, views of its tables."""
    from polyedge.functions import algebra

    algebra.install(spark)
    spark.udf.register("robust_iqr", robust_iqr)
    spark.udf.register("vector_sum", vector_sum)
    spark.udtf.register("lag_windows", LagWindows)
    spark.udtf.register("khop", KHop)
    if sf_dir:
        for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
            spark.read.parquet(f"{sf_dir}/{t}.parquet").createOrReplaceTempView(t)
