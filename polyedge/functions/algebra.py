"""Vector algebra as Column functions, and as inline SQL functions that Catalyst sees through."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, functions as F


def vector(v: Sequence[float]) -> Column:
    return F.array(*[F.lit(float(x)) for x in v])


def matrix(m: np.ndarray) -> Column:
    return F.array(*[vector(r) for r in m])


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def matvec(m: np.ndarray, x: Column) -> Column:
    """Constant matrix times vector."""
    return F.transform(matrix(np.atleast_2d(m)), lambda row: dot(row, x))


def add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def sub(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x - y)


def scale(a: Column, k: Column) -> Column:
    return F.transform(a, lambda x: x * k)


def hadamard(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x * y)


def l2(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def distance(a: Column, b: Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))


def relu(x: Column) -> Column:
    return F.greatest(x, F.lit(0.0))


def sigmoid(x: Column) -> Column:
    return 1 / (1 + F.exp(-x))


def relu_vec(a: Column) -> Column:
    return F.transform(a, relu)


def sigmoid_vec(a: Column) -> Column:
    return F.transform(a, sigmoid)


def sum_vectors(vec: str | Column, d: int, weight: Column | None = None) -> Column:
    """Aggregate: (weighted) sum of arrays of length ``d``, as d scalar sums with partial aggregation."""
    v = F.col(vec) if isinstance(vec, str) else vec
    return F.array(*[F.sum(v[i] * weight if weight is not None else v[i]) for i in range(d)])


def softmax_by(df: DataFrame, keys: Sequence[str], score: str, name: str) -> DataFrame:
    """Append the softmax of ``score`` within each key, stable by the key's maximum."""
    from pyspark.sql import Window

    w = Window.partitionBy(*keys)
    e = F.exp(F.col(score) - F.max(score).over(w))
    return df.withColumn("__e", e).withColumn(name, F.col("__e") / F.sum("__e").over(w)).drop("__e")


INLINE = {
    "vec_dot": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
    "vec_l2": "(a ARRAY<DOUBLE>) RETURNS DOUBLE RETURN sqrt(aggregate(a, 0D, (s, x) -> s + x * x))",
    "vec_add": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE> RETURN zip_with(a, b, (x, y) -> x + y)",
    "vec_scale": "(a ARRAY<DOUBLE>, k DOUBLE) RETURNS ARRAY<DOUBLE> RETURN transform(a, x -> x * k)",
    "relu": "(x DOUBLE) RETURNS DOUBLE RETURN greatest(x, 0D)",
    "sigmoid": "(x DOUBLE) RETURNS DOUBLE RETURN 1 / (1 + exp(-x))",
}


def install(spark: SparkSession) -> None:
    """Register the inline SQL functions in the session."""
    for name, body in INLINE.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
