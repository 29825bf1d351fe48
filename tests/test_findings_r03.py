"""Cases of the third review: each failed before its finding was settled."""

import numpy as np
import pytest
from pyspark.sql import Window, functions as F

from polyedge.baselines import classic
from polyedge.models import autodiff as ad
from polyedge.operators import inject as I
from polyedge.plans import workloads as L


@pytest.mark.parametrize("carrier", [True, False])
def test_testbed_has_38_attacks(spark, sf, carrier):
    _, truth, faults, ticks, n, start = L.injected(spark, sf, "testbed", carrier)
    assert len({f.fault_id for f in faults}) == len({f.sensor_id for f in faults}) == 38
    assert all(int(ticks * start) <= f.t0 <= f.t1 < ticks for f in faults)
    begins = (F.col("y") == 1) & (F.lag("y", 1, 0).over(Window.orderBy("tick")) == 0)
    assert truth.select(begins.alias("b")).where("b").count() == 38


def test_faults_are_shortened_only_where_they_would_meet():
    for ticks in (2000, 500, 90):
        f = I.schedule(ticks, 64, ticks // 2, 38, 8, 14)
        lengths = {a.t1 - a.t0 + 1 for a in f}
        assert len(f) == 38 and lengths == (set(range(8, 15)) if ticks == 2000 else {3} if ticks == 500 else {1})
        assert ticks == 90 or all(a.t1 + 1 < b.t0 for a, b in zip(f, f[1:]))


def test_constants_of_the_tape_get_no_gradient_and_results_stay():
    rng = np.random.default_rng(0)
    h, v = (rng.random((6, 6)) < 0.5).astype(float), ad.Var(rng.random((4, 6, 3)))
    held, win = ad.var(h[None]), ad.var(rng.random((4, 6, 3)))
    seen = []
    held.back = win.back = lambda g: seen.append(g) or ()
    ad.backward(ad.square(held @ v + win * v).sum())
    assert held.grad is None and win.grad is None and not seen
    want = 2 * (h @ v.value + win.value * v.value)
    assert np.allclose(v.grad, h.T @ want + win.value * want, rtol=1e-13)


def test_masked_softmax_takes_powers_of_members_alone(monkeypatch):
    rng = np.random.default_rng(1)
    x, mask = rng.normal(size=(5, 7, 9)), rng.random((7, 9)) < 0.4
    mask[2] = False
    e = np.exp(np.where(mask, x, -np.inf) - np.where(mask, x, -np.inf).max(-1, keepdims=True, initial=-1e9))
    want = e / np.where(mask.any(-1, keepdims=True), e.sum(-1, keepdims=True), 1)
    taken, exp = [], np.exp
    monkeypatch.setattr(np, "exp", lambda a, *o, where=True, **k: taken.append(np.broadcast_to(where, a.shape).sum()) or exp(a, *o, where=where, **k))
    assert np.abs(ad.softmax(ad.var(x), -1, mask).value - want).max() < 1e-15 and taken == [5 * mask.sum()]


def test_neighbour_detectors_sort_only_the_nearest(monkeypatch):
    rng, sort = np.random.default_rng(2), np.argsort
    for d in (rng.random((40, 300)), rng.integers(0, 60, (40, 300)) / 7, np.zeros((40, 300)), np.where(rng.random((40, 300)) < 0.99, np.nan, 1.0), np.full((3, 9), np.inf)):
        for k in (1, 5, d.shape[1] - 1, d.shape[1]):
            assert (classic._smallest(d, k) == sort(d, axis=1, kind="stable")[:, :k]).all()
    monkeypatch.setattr(np, "argsort", lambda *a, **k: pytest.fail("sorts whole rows"))
    assert classic.knn(rng.random((900, 8)), 400).shape == (900, 1)


def test_the_longest_jobs_of_a_leaderboard_begin_first(spark, sf, monkeypatch):
    jobs = []
    monkeypatch.setattr(L, "fan_out", lambda spark, x, names, run: jobs.extend(names) or spark.createDataFrame([], "model string, tick long, flag int"))
    L.leaderboard(spark, sf, "telemetry25")
    assert jobs[:2] == ["proposed", "feature_bagging"] and sorted(jobs) == sorted([*L.B.DETECTORS, "proposed"])
