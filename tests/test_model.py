"""Block model: gradients, rewrites, invariants, the relational path, training and saving."""

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from polyedge.baselines import DETECTORS
from polyedge.baselines.common import detect
from polyedge.models import autodiff as ad, blockmath as bm, params as pm, train as T
from polyedge.models.config import ABLATIONS, ModelConfig, ablation
from polyedge.models.optim import Adam, EarlyStop, HalveOnPlateau
from polyedge.operators import forward as FW, panel as P, structure as S
from polyedge.session import materialise

BASE = ModelConfig(n=5, w=4, k=2, d=3)


@pytest.mark.parametrize("name", [None, *ABLATIONS, "neighbourhood", "fill", "none", "classify", "hidden", "full_ratio"])
def test_gradients_by_central_differences(name):
    extra = {"neighbourhood": {"position": "neighbourhood"}, "fill": {"skip": "fill"}, "none": {"skip": "none"}, "classify": {"head": "classify"}, "hidden": {"hidden": (4,)}, "full_ratio": {"ratio": 1.0}}
    cfg = BASE if name is None else replace(BASE, **extra[name]) if name in extra else ablation(BASE, name)
    rng = np.random.default_rng(0)
    win = rng.random((6, 5, 4))
    y = (rng.random(6) < 0.5).astype(float) if cfg.head == "classify" else rng.random((6, 5))
    p = T.initial(cfg)
    h = bm.incidence(p["z"], cfg)
    f = T.loss_of(win, y, h, cfg)
    _, g = ad.gradients(f, p)
    for k in p:
        for _ in range(3):
            i = tuple(rng.integers(0, s) for s in p[k].shape)
            hi, lo = ({a: b.copy() for a, b in p.items()} for _ in range(2))
            hi[k][i] += 1e-6
            lo[k][i] -= 1e-6
            num = (float(f(bm.as_vars(hi)).value) - float(f(bm.as_vars(lo)).value)) / 2e-6
            assert abs(num - g[k][i]) < 1e-5 * max(1e-2, abs(num) + abs(g[k][i])), (k, i)


@pytest.mark.parametrize("name", [None, *ABLATIONS])
def test_rewrites_change_nothing(name):
    cfg = ablation(BASE, name) if name else BASE
    rng = np.random.default_rng(1)
    win, p = rng.random((7, 5, 4)), T.initial(cfg)
    a = T.predict(win, p, cfg)
    b = T.predict(win, p, replace(cfg, rewrites=False))
    assert np.abs(a - b).max() < 1e-9


def test_mixing_weight_is_inert_under_the_default_score_only():
    rng = np.random.default_rng(2)
    win = rng.random((4, 5, 4))
    for shift, inert in (("difference", True), ("dot", False)):
        cfg = replace(BASE, shift=shift, rewrites=False)
        p = T.initial(cfg)
        a = T.predict(win, p, cfg)
        p["u_mix"] = p["u_mix"] + 1
        assert (np.abs(T.predict(win, p, cfg) - a).max() < 1e-9) == inert


def test_sensor_order_does_not_matter():
    rng = np.random.default_rng(3)
    win, p, order = rng.random((4, 5, 4)), T.initial(BASE), np.array([3, 0, 4, 1, 2])
    a = T.predict(win, p, BASE)
    q = {k: v.copy() for k, v in p.items()}
    q["z"], q["pos"] = p["z"][order], p["pos"][order]
    w = p["head_w"].reshape(5, 5, 3)[order][:, order]
    q["head_w"], q["head_b"] = w.reshape(5, 15), p["head_b"][order]
    assert np.abs(T.predict(win[:, order], q, BASE) - a[:, order]).max() < 1e-9


def test_block_path_equals_relational_path(spark):
    cfg = replace(BASE, k=2)
    p = pm.formula(cfg)
    rng = np.random.default_rng(4)
    x = rng.random((12, 5))
    rows = [(int(t), i, float(x[t, i])) for t in range(12) for i in range(5)]
    panel = spark.createDataFrame(rows, "tick long, sensor_id int, value double")
    from polyedge.operators.windows import lagged

    nodes = spark.createDataFrame([(i, [float(v) for v in z]) for i, z in enumerate(p["z"])], "sensor_id int, z array<double>")
    members = materialise(S.build(nodes, k=2))
    h = np.zeros((5, 5))
    for r in members.collect():
        h[r.edge_id, r.sensor_id] = 1
    assert (h == bm.knn_incidence(p["z"], 2)).all() and h.sum() == 15
    for name in (None, "no_embedding", "no_attention", "projection_score", "no_gate", "dot_shift", "no_position", "sinusoidal_position"):
        c = ablation(cfg, name) if name else cfg
        q = pm.formula(c)
        r = materialise(FW.encode_decode(lagged(panel, 4), members, q, c).nodes)
        got = FW.forecast(FW.Refined(r, r), q, c).collect()
        q["head_b"] = np.zeros(5)
        _, win, _ = T.windows(x, 4)
        hb = bm.as_vars(q)
        want = bm.forecast(win, h, hb, c).value
        assert len(got) == 40
        assert max(abs(g.y_hat - want[g.tick - 4, g.sensor_id]) for g in got) < 1e-9, name


def test_pool_keeps_structure_at_ratio_one():
    x = ad.Var(np.random.default_rng(5).random((2, 5, 3)))
    p = bm.as_vars(T.initial(BASE))
    _, mask = bm.pool(x, bm.incidence(p["z"].value, BASE), p, replace(BASE, ratio=1.0))
    assert mask.all()
    _, mask = bm.pool(x, bm.incidence(p["z"].value, BASE), p, replace(BASE, ratio=0.5))
    assert (mask.sum(1) == 3).all()


def test_six_node_pool_and_unpool(spark):
    six = {1: {1, 2, 3}, 2: {2, 3}, 3: {3, 5, 6}, 4: {1, 4}, 5: {4, 5}, 6: {5, 6}}
    members = spark.createDataFrame([(e, s) for e, m in six.items() for s in m], "edge_id int, sensor_id int")
    kept = spark.createDataFrame([(0, s) for s in (1, 3, 4, 5)], "tick int, sensor_id int")
    got = {}
    for r in FW.induce(members, kept).collect():
        got.setdefault(r.edge_id, set()).add(r.sensor_id)
    assert got == {1: {1, 3}, 3: {3, 5}, 4: {1, 4}, 5: {4, 5}}
    nodes = spark.createDataFrame([(0, s) for s in six], "tick int, sensor_id int")
    back = FW.scatter(kept.withColumn("x", F.array(F.lit(1.0), F.lit(2.0))), nodes, 2).collect()
    assert {r.sensor_id: r.x for r in back}[2] == [0.0, 0.0] and {r.sensor_id: r.x for r in back}[3] == [1.0, 2.0]


def waves(ticks=400, n=6):
    t, i = np.arange(ticks)[:, None], np.arange(n)
    return 0.5 + 0.35 * np.sin(2 * np.pi * (t - i // 5) / (12 + 4 * (i % 5)))


def test_training_lowers_the_loss_and_beats_the_last_value():
    x = waves()
    cfg = ModelConfig(n=6, w=8, k=2, d=8)
    params, history = T.fit(x, 240, 80, cfg, epochs=60, lr=1e-2)
    assert history[-1] < history[0] / 3
    at, win, y = T.windows(x, 8)
    test = at >= 320
    mine = ((T.predict(win[test], params, cfg) - y[test]) ** 2).mean()
    assert mine < ((win[test][:, :, -1] - y[test]) ** 2).mean() / 2


def test_classifier_head_learns():
    x = waves()
    labels = np.zeros(400)
    for a in range(20, 400, 40):
        labels[a : a + 8] = 1
        x[a : a + 8, 2] += 0.5
    cfg = ModelConfig(n=6, w=8, k=2, d=4, head="classify")
    params, history = T.fit(x, 300, 60, cfg, labels=np.roll(labels, 1), epochs=30, lr=1e-2)
    assert min(history) < history[0] - 0.01
    p = T.predict(T.windows(x, 8)[1], params, cfg)
    assert p.shape == (392,) and ((p >= 0) & (p <= 1)).all()


def test_optimiser_schedule():
    opt, halve, stop = Adam(1.0), HalveOnPlateau(2), EarlyStop(3)
    for loss in [1.0, 1.0, 1.0]:
        halve.update(loss, opt)
    assert opt.lr == 0.5
    assert [stop.update(v, {"a": np.zeros(1)}) for v in [1.0, 0.5, 0.6, 0.6, 0.6]] == [False, False, False, False, True]


def vectors(spark, x):
    return spark.createDataFrame([(t, [float(v) for v in r]) for t, r in enumerate(x)], "tick long, x array<double>")


@pytest.mark.parametrize("chunk", [32, 1000])
def test_chunked_scoring_equals_one_pass(spark, chunk):
    x = waves(150)
    cfg = ModelConfig(n=6, w=8, k=2, d=4)
    p = T.initial(cfg)
    at, win, y = T.windows(x, 8)
    want = T.predict(win, p, cfg)
    got = T.score_blocks(vectors(spark, x), p, cfg, chunk).collect()
    assert len(got) == len(at) * 6
    assert max(abs(r.y_hat - want[r.tick - 8, r.sensor_id]) for r in got) < 1e-9


def test_large_batch_gradient_is_the_mean(spark):
    x = waves(150)
    cfg = ModelConfig(n=6, w=8, k=2, d=4)
    p = T.initial(cfg)
    at, win, y = T.windows(x, 8)
    on = at < 100
    loss, want = ad.gradients(T.loss_of(win[on], y[on], bm.incidence(p["z"], cfg), cfg), {k: v for k, v in p.items() if not k.startswith("cls")})
    chunks = T.chunk_rows(vectors(spark, x), 8, 32).repartition("chunk").sortWithinPartitions("chunk", "tick")
    T.ship(spark)
    got_loss, got = T.gradient_round(chunks, p, cfg, 100)
    assert got_loss == pytest.approx(loss)
    assert max(np.abs(got[k] - want[k]).max() for k in want) < 1e-10
    _, history = T.fit_large_batch(vectors(spark, x), 100, cfg, rounds=4)
    assert history[-1] < history[0]


def test_parameters_save_and_load(spark, tmp_path):
    p = T.initial(BASE)
    pm.save(spark, p, str(tmp_path / "params"), "run", 3)
    q = pm.load(spark.read.parquet(str(tmp_path / "params")), "run", 3)
    assert all((p[k] == q[k]).all() for k in p)


@pytest.mark.parametrize("name", sorted(DETECTORS))
def test_detectors_score_every_row(name):
    x = waves(220, 5) + 0.02 * np.random.default_rng(1).random((220, 5))
    x[190:196] += 0.8
    dev = DETECTORS[name][0](x, 130, 1)
    assert dev.shape[0] == 220 and np.isfinite(dev).all()
    assert detect(dev, 130, 44, first=8).shape == (220,)
    assert (dev == DETECTORS[name][0](x, 130, 1)).all()


@pytest.mark.parametrize("name", ["principal_components", "nearest_neighbours", "vector_autoregression", "local_outlier_factor"])
def test_detectors_see_a_large_step(name):
    x = waves(300, 5)
    x[260:268] += 1.0
    dev = DETECTORS[name][0](x, 180, 1).max(1)
    assert dev[260:268].max() > 3 * np.percentile(dev[180:240], 95)


def test_lsh_finds_most_neighbours(spark):
    rng = np.random.default_rng(6)
    z = rng.normal(size=(80, 8))
    nodes = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(z)], "sensor_id int, z array<double>")
    exact = {(r.edge_id, r.sensor_id) for r in S.knn(S.pair_distances(nodes), 3).collect()}
    near = {(r.edge_id, r.sensor_id) for r in S.knn_lsh(nodes, 3, bucket=4.0, tables=12).collect()}
    assert len(exact & near) / len(exact) > 0.9


def test_vector_layout(spark, sf):
    v = P.to_vectors(P.panel(spark, sf, "event_meter")).first()
    assert len(v.x) == 10
