"""Panels, deviation, measures, traces, control, streaming, sources, plans and isolation."""

import shutil
import subprocess
import sys
from datetime import datetime
from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

from polyedge import session, sources
from polyedge.baselines.common import detect as detect_rows
from polyedge.models import train as T
from polyedge.models.config import ModelConfig
from polyedge.operators import deviation as V, diagnose as G, inject as I, metrics as N, panel as P, prescribe as C, relational as R, windows as W
from polyedge.plans import optimizer as O
from polyedge.sources import simulated
from polyedge import streaming as ST

ROOT = Path(__file__).resolve().parents[1]


def small(spark, ticks=60, n=3):
    rows = [(t, i, float((t * (i + 2)) % 7)) for t in range(ticks) for i in range(n)]
    return spark.createDataFrame(rows, "tick long, sensor_id int, value double")


def test_chunked_windows_equal_plain_ones(spark):
    p = small(spark)
    a = sorted(W.lagged(p, 5).collect())
    for chunk in (1, 4, 7, 100):
        assert sorted(W.lagged(p, 5, chunk).collect()) == a
    assert len(a) == 55 * 3


def test_batches_cover_every_tick_once(spark):
    b = W.batches(small(spark), 8, 1, 0)
    sizes = [r["count"] for r in b.groupBy("batch").count().collect()]
    assert sum(sizes) == 60 and max(sizes) == 8


def test_scaling_bounds_and_constant(spark):
    p = P.with_split(small(spark).union(spark.createDataFrame([(t, 9, 4.0) for t in range(60)], "tick long, sensor_id int, value double")))
    s = P.apply_minmax(p, P.fit_minmax(p))
    train = s.where("split = 'train'").agg(F.min("value"), F.max("value")).first()
    assert (train[0], train[1]) == (0.0, 1.0)
    assert s.where("sensor_id = 9").agg(F.max("value")).first()[0] == 0.0
    clipped = P.apply_minmax(p.withColumn("value", F.col("value") * 3), P.fit_minmax(p), clip=True)
    assert clipped.agg(F.max("value")).first()[0] == 1.0


def test_smoothing_of_a_constant(spark):
    t = spark.range(40).select(F.col("id").alias("tick"), F.lit(2.0).alias("raw"))
    assert {r.smooth for r in V.smooth(t).collect()} == {2.0}
    printed = {r.tick: r.smooth for r in V.smooth(t, 10, "printed").collect()}
    assert printed[39] == pytest.approx(2.4)
    for mode in ("trailing", "printed"):
        a = {r.tick: r.smooth for r in V.smooth(t, 10, mode).collect()}
        assert {r.tick: pytest.approx(r.smooth) for r in V.smooth(t, 10, mode, chunk=6).collect()} == a


def test_numpy_detection_equals_spark(spark):
    rng = np.random.default_rng(2)
    dev = rng.random((100, 4))
    dev[88:92, 2] += 3
    rows = [(t, i, "train" if t < 50 else "validation" if t < 75 else "test", float(dev[t, i]), 0.0) for t in range(100) for i in range(4)]
    f = spark.createDataFrame(rows, "tick long, sensor_id int, split string, y double, y_hat double")
    _, ticks, threshold = V.detect(f)
    flags = {r.tick: r.flag for r in V.flag(ticks, threshold).collect()}
    want = detect_rows(dev, 50, 25)
    assert flags == {t: int(want[t]) for t in range(75, 100)} and sum(flags.values()) > 0


def test_segment_adjustment(spark):
    y = [0, 1, 1, 1, 0, 1, 1, 0, 0]
    f = [1, 0, 1, 0, 0, 0, 0, 1, 0]
    rows = spark.createDataFrame(list(zip(range(9), y, f)), "tick long, y int, flag int")
    got = [r.flag for r in N.adjust_segments(rows).orderBy("tick").collect()]
    assert got == [1, 1, 1, 1, 0, 0, 0, 1, 0]
    raw, adj = (N.prf(N.confusion(x)).first() for x in (rows, N.adjust_segments(rows)))
    assert adj.recall >= raw.recall and adj.tn == raw.tn
    assert min(raw.precision, raw.recall) <= raw.f1 <= max(raw.precision, raw.recall)
    runs = spark.createDataFrame([("a", 1.0), ("a", 3.0)], "m string, f1 double")
    assert N.mean_runs(runs, ["m"], ["f1"]).first().f1 == 2.0


def test_trace_of_the_six_node_example(spark):
    from polyedge.queries.methods import six_node

    roots = spark.createDataFrame([(0,)], "root int")
    for hops in (None, 2, 5):
        t = {(r.hop, r.to_id + 1) for r in G.propagate(six_node(spark), roots, hops).collect()}
        assert t == {(1, 2), (1, 3), (1, 4), (2, 5), (2, 6)}
    trace = G.propagate(six_node(spark), roots, 2)
    att = six_node(spark).withColumn("coef", F.lit(0.5))
    score = spark.createDataFrame([(i, float(i)) for i in range(6)], "sensor_id int, score double")
    top = G.salient(trace, att, score, 1).first()
    assert top.to_id == 5
    f = spark.createDataFrame([(7, i, 1.0, 0.5) for i in range(6)], "tick long, sensor_id int, y double, y_hat double")
    p = spark.createDataFrame([(t, i, float(t * (1 if i % 2 else -1))) for t in range(9) for i in range(6)], "tick long, sensor_id int, value double")
    signs = {r.sensor_id: r.sign for r in G.evidence(f, trace, p, 7).collect()}
    assert signs[0] == 1.0 and signs[1] == -1.0


def test_control_search_reaches_the_grid_optimum():
    t, i = np.arange(240)[:, None], np.arange(4)
    x = 0.5 + 0.35 * np.sin(2 * np.pi * (t - i) / 12)
    cfg = ModelConfig(n=4, w=6, k=2, d=4)
    params, _ = T.fit(x, 180, 40, cfg, epochs=8, lr=1e-2)
    ctx = C.Context(params, cfg, x[-7:-1], x[-1:], np.zeros(4), np.full(4, 0.1), 1)
    for horizon, steps in ((1, 81), (2, 41)):
        now = C.Context(params, cfg, x[-8:-2], x[-2:], ctx.med, ctx.iqr, 1) if horizon == 2 else ctx
        _, loss, history = C.search(now, horizon, s=C.Search(generations=20 * horizon))
        _, best = C.grid(now, horizon, steps)
        assert loss <= best / 0.95 + 1e-9 and history == sorted(history, reverse=True)


def test_control_search_runs_incidents_in_parallel(spark):
    x = np.random.default_rng(3).random((40, 3))
    cfg = ModelConfig(n=3, w=4, k=1, d=2)
    ctx = C.Context(T.initial(cfg), cfg, x[:4], x[4:6], np.zeros(3), np.ones(3), 0)
    other = C.Context(ctx.params, cfg, x[10:14], x[14:16], ctx.med, ctx.iqr, 2)
    for objective in ("score", "tracking"):
        got = {r.incident: r for r in C.search_many(spark, [ctx, other, ctx], 2, objective, C.Search(generations=30)).collect()}
        assert len(got) == 3 and got[0].recommended == got[2].recommended
        for i, c in enumerate((ctx, other, ctx)):
            assert got[i].after == pytest.approx(C.fitness(np.array([got[i].recommended]), c, objective)[0])
            assert got[i].after <= C.grid(c, 2, 21, objective)[1] * 1.05 + 1e-9


def test_drift_counts_repeats_and_one_sided_keys(spark):
    rows = lambda x: spark.createDataFrame(x, "k string, v double")
    got = {r.k: r for r in R.drift(rows([("a", 1.0), ("a", 1.0), ("a", 2.0), ("b", 5.0), ("d", None)]), rows([("a", 1.0), ("a", 3.0), ("c", 0.0)]), "k", "v").collect()}
    assert got["a"].distance == pytest.approx(0.5) and (got["a"].before, got["a"].after) == (3, 2)
    assert got["b"].distance is None and got["c"].distance is None and "d" not in got


def test_median_fill(spark):
    day = lambda d: datetime(2024, 1, d)
    rows = spark.createDataFrame([(day(3), "a", 4.0), (day(5), "a", 8.0), (day(1), "b", 1.0), (day(10), "b", 9.0), (day(9), "c", 7.0)], "ts timestamp_ntz, sensor_name string, value double")
    got = {(r.sensor_id, r.tick): r.value for r in P.densify(rows, "day", "median").collect()}
    # a: median of 4 and 8 before its first; c has no reading in the first six ticks
    assert [got[0, t] for t in range(10)] == [6.0, 6.0, 4.0, 4.0, 8.0, 8.0, 8.0, 8.0, 8.0, 8.0]
    assert [got[1, t] for t in range(10)] == [1.0] * 9 + [9.0]
    assert [got[2, t] for t in range(10)] == [0.0] * 8 + [7.0] * 2


def test_smoothing_in_ranges_equals_one_window(spark):
    ticks = spark.range(95).select(F.col("id").alias("tick"), F.pmod(F.col("id") * 37, F.lit(11)).cast("double").alias("raw"))
    for mode in ("trailing", "printed"):
        whole = V.smooth(ticks, 10, mode, None).collect()
        assert sorted(V.smooth(ticks, 10, mode, 7).collect()) == sorted(whole) == sorted(V.smooth(ticks, 10, mode).collect())


def test_segments_over_borders_of_ranges(spark):
    rng = np.random.default_rng(9)
    rows = [(m, t, int(y), int(f)) for m in ("a", "b") for t, (y, f) in enumerate(zip(rng.random(90) < 0.7, rng.random(90) < 0.15, strict=True)) if t % 13 or m == "b"]
    want, run = {}, []
    for m, t, y, f in [*rows, ("c", 0, 0, 0)]:
        if run and (not y or m != run[0][0]):
            want |= {k: max(x for _, _, x in run) for k in [(a, b) for a, b, _ in run]}
            run = []
        if y:
            run.append((m, t, f))
        else:
            want[m, t] = f
    want.pop(("c", 0))
    df = spark.createDataFrame(rows, "model string, tick long, y int, flag int")
    for chunk in (1, 4, 7, 1000):
        out = N.adjust_segments(df, ["model"], chunk)
        assert out.columns == df.columns and {(r.model, r.tick): r.flag for r in out.collect()} == want


def test_late_rows_go_to_the_side(spark):
    df = spark.createDataFrame([(datetime(2024, 1, 1, h), h) for h in range(6)], "ts timestamp, v int")
    main, late = ST.with_lateness(df, "2024-01-01 03:00:00")
    assert sorted(r.v for r in main.collect()) == [3, 4, 5] and sorted(r.v for r in late.collect()) == [0, 1, 2]


def test_schedule_and_faults(spark):
    f = I.schedule(500, 12, 250, 10, 1, 3)
    assert all(250 <= a.t0 <= a.t1 < 500 for a in f)
    assert all(b.t0 - a.t1 >= 5 for a, b in zip(f, f[1:]))
    p = spark.createDataFrame([(t, i, 0.0) for t in range(240, 500) for i in range(12)], "tick long, sensor_id int, value double")
    clean = I.with_carrier(p)
    hit = I.apply_faults(clean, I.fault_rows(spark, f), 12)
    assert hit.count() == clean.count()
    changed = hit.alias("a").join(clean.alias("b"), ["tick", "sensor_id"]).where("abs(a.value - b.value) > 1e-12").select("tick").distinct()
    truth = I.truth(spark, f, 500).where("y = 1").select("tick")
    assert changed.exceptAll(truth).isEmpty() and changed.count() > 5


def test_stream_equals_batch(spark, tmp_path):
    rng = np.random.default_rng(5)
    x = 0.5 + 0.3 * np.sin(np.arange(60)[:, None] / 3 + np.arange(3)) + 0.01 * rng.random((60, 3))
    x[50:54, 1] += 1
    cfg = ModelConfig(n=3, w=5, k=1, d=2)
    params = T.initial(cfg)
    at, win, y = T.windows(x, 5)
    dev = np.abs(T.predict(win, params, cfg) - y)
    med, iqr = np.median(dev, 0), np.percentile(dev, 75, axis=0) - np.percentile(dev, 25, axis=0)
    top = ((dev - med) / iqr).max(1)
    smooth = [top[max(0, k - 9) : k + 1].mean() for k in range(len(top))]
    detector = ST.OnlineDetector(params, cfg, med, iqr, float(np.percentile(smooth, 80)))
    schema = "plant string, tick long, x array<double>"
    for k in range(0, 60, 7):
        rows = [("a", t, [float(v) for v in x[t]]) for t in range(k, min(60, k + 7))]
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    q = ST.online_detector(stream, detector).writeStream.foreachBatch(sources.idempotent(str(tmp_path / "out"))).option("checkpointLocation", str(tmp_path / "ck")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    got = {r.tick: (r.score, r.smooth, r.flag) for r in spark.read.option("basePath", str(tmp_path / "out")).parquet(str(tmp_path / "out") + "/*").collect()}
    assert sorted(got) == at.tolist()
    for k, t in enumerate(at):
        assert got[t][0] == pytest.approx(top[k]) and got[t][1] == pytest.approx(smooth[k])


def test_stream_ticks_dedup_and_late_rows(spark, tmp_path):
    rows = [(1, "2024-01-01 00:10:00", "a", 1.0), (1, "2024-01-01 00:10:00", "a", 1.0), (2, "2024-01-01 05:00:00", "a", 2.0), (5, "2024-01-01 05:30:00", "a", 4.0), (3, "2024-01-01 00:20:00", "a", 9.0), (4, "2024-01-01 09:00:00", "a", 1.0)]
    for k, batch in enumerate([rows[:2], rows[2:3], rows[3:4], rows[4:5], rows[5:]]):
        d = spark.createDataFrame(batch, "event_id int, ts string, k string, v double").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
        d.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        import time

        time.sleep(1.1)
    schema = "event_id int, ts timestamp_ntz, k string, v double"
    s = sources.stream(spark, str(tmp_path / "in"), schema)
    out = ST.ticks(ST.dedup(s, "event_id", "1 hour"), "1 hour", "k", "v")
    q = out.writeStream.format("memory").queryName("ticks_out").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination(120)
    got = {(r.start.hour, r.value) for r in spark.table("ticks_out").collect()}
    assert (0, 1.0) in got, got
    assert all(v != 9.0 and v != 10.0 for _, v in got)


def test_sources_round_trip(spark, tmp_path):
    d = spark.createDataFrame([(1, "a"), (2, "b")], "x int, y string")
    for fmt in ("parquet", "orc", "json", "csv"):
        sources.write(d, str(tmp_path / fmt), fmt, partition_by=[])
        back = sources.read(spark, fmt, str(tmp_path / fmt), "x int, y string")
        assert sorted(back.collect()) == sorted(d.collect())
    session.ship(spark)
    simulated.register(spark)
    s = spark.readStream.format("simulated_sensors").option("sensors", 2).load()
    q = s.writeStream.format("memory").queryName("sim").start()
    q.awaitTermination(8)
    q.stop()
    assert spark.table("sim").count() > 0


def test_plans(spark, sf):
    df = sources.table(spark, sf, "lineitem", ["l_quantity"], "l_discount > 0.05")
    assert any("l_discount" in f for f in O.pushed_filters(df))
    assert all("l_comment" not in c and "l_tax" not in c for c in O.read_columns(df))
    panel = P.build_panel(sources.table(spark, sf, "events"), "ts", "event_type", {"n": "count(*)"}, "hour")
    assert O.exchanges(panel) == 1 and not O.has_cartesian(panel)
    big, little = sources.table(spark, sf, "lineitem"), sources.table(spark, sf, "supplier")
    j = R.join(big, little, big.l_suppkey == little.s_suppkey, strategy="broadcast")
    assert O.exchanges(j) == 0


def test_repository_works_without_the_text_operators(tmp_path):
    shutil.copytree(ROOT, tmp_path / "r", ignore=shutil.ignore_patterns(".git", "llm", "corpus_pipeline.py", "__pycache__"))
    code = "import __spark_entry__ as e; q = e.queries(); assert len(q) > 80 and not any(k.startswith('op') or k == 'pipeline' for k in q); assert set(e.oracle_sql()) <= set(q)"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path / "r", check=True, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": str(tmp_path / "r"), "HOME": "/tmp"})
    assert "llm" not in "".join(p.read_text() for p in (ROOT / "polyedge").rglob("*.py") if "llm" not in p.parts)
