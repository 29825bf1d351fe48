"""Detectors as Spark plans against the same detectors on arrays."""

import numpy as np
import pytest

from polyedge.baselines import classic, distributed as B


@pytest.fixture(scope="module")
def rows(spark):
    rng = np.random.default_rng(3)
    t = np.arange(240)[:, None]
    x = np.sin(t / 7 + np.arange(4)) + 0.1 * rng.normal(size=(240, 4))
    x[220] += 3
    split = ["train"] * 160 + ["validation"] * 30 + ["test"] * 50
    return x, spark.createDataFrame([(i, s, [float(v) for v in r]) for i, (s, r) in enumerate(zip(split, x))], "tick long, split string, x array<double>")


def by_tick(df, value="score"):
    return {r["tick"]: r[value] for r in df.collect()}


@pytest.mark.parametrize("block", [1024, 37])
def test_nearest_equals_all_distances(rows, block):
    x, df = rows
    got = B.nearest(df.where("split = 'test'"), df.where("split = 'train'"), 5, block).collect()
    for q in range(190, 240):
        d = np.round(np.sqrt(((x[q] - x[:160]) ** 2).sum(1)), 9)
        best = np.lexsort((np.arange(160), d))[:5]
        mine = sorted((r["rank"], r.j, r.dist) for r in got if r.q == q)
        assert [m[1] for m in mine] == best.tolist() and np.allclose([m[2] for m in mine], d[best])


def test_scores_equal_the_array_forms(rows):
    x, df = rows
    test = range(190, 240)
    knn, lof = by_tick(B.knn_score(df, 5)), by_tick(B.lof(df, 10))
    want_knn, want_lof = classic.knn(x, 160, k=5), classic.lof(x, 160, k=10)
    assert np.allclose([knn[t] for t in test], want_knn[190:, 0], atol=1e-6)
    assert np.allclose([lof[t] for t in test], want_lof[190:, 0], atol=1e-5)
    assert max(knn, key=knn.get) == 220


def test_residuals_equal_the_array_forms(rows):
    x, df = rows
    pca = {(r.tick, r.sensor_id): r.dev for r in B.pca_residual(df).collect()}
    var = {(r.tick, r.sensor_id): r.dev for r in B.var_residual(df, 2, chunk=50).collect()}
    want_pca, want_var = classic.pca(x, 160), classic.vector_autoregression(x, 160, lag=2)
    assert len(pca) == len(var) == 200
    assert all(np.isclose(v, want_pca[k]) for k, v in pca.items())
    assert all(np.isclose(v, want_var[k]) for k, v in var.items())


def test_subsets_hold_half_to_all():
    for n in (1, 2, 6, 51):
        for s in B.subsets(n, 12):
            assert max(1, n // 2) <= len(s) <= n and len(set(s)) == len(s)


def test_no_rows(rows):
    _, df = rows
    assert B.knn_score(df.limit(0)).count() == 0 and B.lof(df.where("split = 'test'")).count() == 0
