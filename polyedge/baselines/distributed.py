"""Comparison detectors as Spark plans, over rows (tick, split, x) with one array of readings a tick.

Neighbours are found block by block: queries and references are dealt by hash to blocks of bounded
size, each pair of blocks is compared in a task of its own (``cogroup``), and only the k best of a query
and block leave it.  Models of sensors (components, regressions) are sums over ticks, whose size is set
by the number of sensors alone, solved on the driver and applied as expressions.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window, functions as F

from polyedge.functions import algebra as A
from polyedge.operators.windows import with_halo

DIGITS = 9  # distances are compared at so many digits, so that ties are ties in every engine


def nearest(queries: DataFrame, references: DataFrame, k: int, block: int = 1024) -> DataFrame:
    """(q, j, dist, rank): the k nearest references of each query, not itself; ties by tick."""
    blocks = [max(1, -(-df.count() // block)) for df in (queries, references)]

    def dealt(df: DataFrame, own: int, other: int, name: str) -> DataFrame:
        mine, all_others = F.pmod(F.xxhash64("tick"), F.lit(blocks[own])), F.explode(F.sequence(F.lit(0), F.lit(blocks[other] - 1)))
        names = ("qb", "rb") if own == 0 else ("rb", "qb")
        return df.select(F.col("tick").alias(name), F.col("x").alias(f"x_{name}"), mine.cast("int").alias(names[0]), all_others.alias(names[1]))

    def compare(q: pd.DataFrame, r: pd.DataFrame) -> pd.DataFrame:
        if not len(q) or not len(r):
            return pd.DataFrame({"q": pd.Series(dtype="int64"), "j": pd.Series(dtype="int64"), "dist": pd.Series(dtype="float64")})
        r = r.sort_values("j")
        y, ids, at = np.stack(r["x_j"]), r["j"].to_numpy(), q["q"].to_numpy()
        out = []
        for s in range(0, len(q), 64):
            x = np.stack(q["x_q"].iloc[s : s + 64])
            d = np.round(np.sqrt(((x[:, None] - y) ** 2).sum(2)), DIGITS)
            d[at[s : s + 64, None] == ids] = np.inf
            best = np.argsort(d, axis=1, kind="stable")[:, :k]
            dist = np.take_along_axis(d, best, 1)
            row, col = np.nonzero(np.isfinite(dist))
            out.append(pd.DataFrame({"q": at[s : s + 64][row], "j": ids[best[row, col]], "dist": dist[row, col]}))
        return pd.concat(out)

    cells = dealt(queries, 0, 1, "q").groupBy("qb", "rb").cogroup(dealt(references, 1, 0, "j").groupBy("qb", "rb"))
    near = cells.applyInPandas(compare, "q long, j long, dist double")
    rank = F.row_number().over(Window.partitionBy("q").orderBy("dist", "j"))
    return near.withColumn("rank", rank).where(F.col("rank") <= k)


def knn_score(vectors: DataFrame, k: int = 5) -> DataFrame:
    """(tick, score): distance of each test tick to its k-th nearest training tick."""
    near = nearest(vectors.where("split = 'test'"), vectors.where("split = 'train'"), k)
    return near.groupBy(F.col("q").alias("tick")).agg(F.max("dist").alias("score"))


def lof(vectors: DataFrame, k: int = 10) -> DataFrame:
    """(tick, score): mean density of a test tick's neighbours over its own, against training ticks."""
    train = vectors.where("split = 'train'")
    near = nearest(vectors.where("split IN ('train', 'test')"), train, k)
    reach = near.groupBy(F.col("q").alias("j")).agg(F.max("dist").alias("reach"))
    density = near.join(reach, "j").groupBy("q").agg((1 / F.greatest(F.avg(F.greatest("dist", "reach")), F.lit(1e-12))).alias("density"))
    of_neighbour = density.select(F.col("q").alias("j"), F.col("density").alias("theirs"))
    test = vectors.where("split = 'test'").select(F.col("tick").alias("q"))
    means = near.join(test, "q", "left_semi").join(of_neighbour, "j").groupBy("q").agg(F.avg("theirs").alias("theirs"))
    return means.join(density, "q").select(F.col("q").alias("tick"), (F.col("theirs") / F.col("density")).alias("score"))


def subsets(n: int, rounds: int) -> list[list[int]]:
    """Sensors of each round: between half and all of them, by integer arithmetic."""
    least = max(1, n // 2)
    return [sorted(sorted(range(n), key=lambda i: ((i * 7919 + s * 104729 + 17) % 10007, i))[: least + s % (n - least + 1)]) for s in range(rounds)]


def bagging(vectors: DataFrame, n: int, rounds: int = 3, k: int = 10) -> DataFrame:
    """(tick, score): sum of density ratios over subsets of the sensors."""
    parts = [lof(vectors.withColumn("x", F.array(*[F.col("x")[i] for i in s])), k) for s in subsets(n, rounds)]
    total = parts[0]
    for p in parts[1:]:
        total = total.unionByName(p)
    return total.groupBy("tick").agg(F.sum("score").alias("score"))


def _moments(rows: DataFrame, left: str, right: str) -> np.ndarray:
    """Sum over rows of the outer product of two array columns; the driver gets one row for each place."""
    a = rows.select(F.posexplode(left).alias("i", "a"), F.col(right).alias("__r")).select("i", "a", F.posexplode("__r").alias("j", "b"))
    got = a.groupBy("i", "j").agg(F.sum(F.col("a") * F.col("b")).alias("s")).toPandas()
    out = np.zeros((int(got["i"].max()) + 1, int(got["j"].max()) + 1))
    out[got["i"], got["j"]] = got["s"]
    return out


def _residuals(rows: DataFrame, forecast) -> DataFrame:
    """(tick, sensor_id, dev): distance of each reading to its forecast."""
    dev = F.transform(A.sub(F.col("x"), forecast), lambda v: F.abs(v))
    return rows.select("tick", F.posexplode(dev).alias("sensor_id", "dev"))


def pca_residual(vectors: DataFrame, keep: float = 0.9) -> DataFrame:
    """Residual of each test tick outside the components that hold ``keep`` of the training variance."""
    train = vectors.where("split = 'train'").withColumn("f", F.concat("x", F.array(F.lit(1.0))))
    m = _moments(train, "f", "f")
    count, mean = m[-1, -1], m[-1, :-1] / m[-1, -1]
    value, vector = np.linalg.eigh((m[:-1, :-1] - count * np.outer(mean, mean)) / max(count - 1, 1))
    order = np.argsort(-value)
    v = vector[:, order[: int(np.searchsorted(np.cumsum(value[order]) / max(value.sum(), 1e-12), keep)) + 1]]
    inside = v @ v.T
    forecast = A.add(A.matvec(inside, F.col("x")), A.vector(mean - inside @ mean))
    return _residuals(vectors.where("split = 'test'"), forecast)


def var_residual(vectors: DataFrame, lag: int = 1, ridge: float = 1e-3, chunk: int = 500) -> DataFrame:
    """Residual of each test tick of a ridge regression on the last ``lag`` ticks, fitted on training ticks."""
    w = Window.partitionBy("__chunk").orderBy("tick")
    rows = with_halo(vectors, lag, chunk).withColumn("f", F.concat(*[F.lag("x", b).over(w) for b in range(lag, 0, -1)], F.array(F.lit(1.0))))
    rows = rows.where(F.col("__own") & F.col("f").isNotNull())
    train = rows.where("split = 'train'")
    gram, target = _moments(train, "f", "f"), _moments(train, "f", "x")
    coef = np.linalg.solve(gram + ridge * np.eye(len(gram)), target)
    return _residuals(rows.where("split = 'test'"), A.matvec(coef.T, F.col("f")))


def to_rows(scores: DataFrame, columns: Sequence[str] = ("tick", "score"), digits: int = 5) -> DataFrame:
    return scores.select(*columns[:-1], F.round(columns[-1], digits).alias(columns[-1]))
