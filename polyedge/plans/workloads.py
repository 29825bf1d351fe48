"""The experiment workloads on the given tables: accuracy, faults, ablation, leaderboard, control."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F

from polyedge import baselines as B
from polyedge.baselines.common import detect as detect_rows
from polyedge.models import train as T
from polyedge.models.config import ABLATIONS, PRESETS, ModelConfig
from polyedge.operators import deviation as V, diagnose as G, forward as FW, inject as I, metrics as N, panel as P, prescribe as C, structure as S, windows as W
from polyedge.session import configure, keep_freed, materialise, ship

#: faults of each experiment set: start of the test part, number, shortest and longest; as long as the
#: ten ticks of smoothing or longer, for shorter ones leave most flags behind the fault
FAULTS = {
    "plant": (0.6, 3, 15, 24),
    "network": (0.6, 3, 15, 24),
    "telemetry25": (0.8, 2, 8, 12),
    "telemetry50": (0.8, 4, 8, 14),
    "simulator": (0.8, 1, 40, 40),
    "testbed": (0.5, 38, 8, 14),
}
#: width, window and epochs at which the workloads run as queries; a full run takes d=128 and 100 epochs
LIGHT = {"d": 8}
WINDOW = {"plant": 20, "network": 20}
EPOCHS, RATE = 50, 1e-2
#: the comparison of detection rates by fault: the nine neural methods of the table, then three plain ones
RIVALS = (
    "transformer", "transformer_encoder", "lstm_error", "temporal_convolution", "fourier_mixing", "graph_transformer",
    "pair_graph_deviation", "graph_attention_forecast", "relation_learning", "principal_components", "vector_autoregression", "last_value",
)
#: jobs of a leaderboard that take longest on large panels
LONGEST = ("proposed", "feature_bagging", "graph_attention_forecast", "pair_graph_deviation", "adversarial_recurrent", "relation_learning", "autoencoder_ensemble")
#: clean ticks before each fault programme when one trained model scores them all
LEAD = 64


def injected(spark: SparkSession, sf_dir: str, preset: str, carrier: bool = True) -> tuple[DataFrame, DataFrame, list[I.Fault], int, int, float]:
    """Panel with faults, truth, schedule, ticks, sensors and the training share.

    Without ``carrier`` the faults lie on the scaled readings themselves, in the kinds that need none.
    """
    name = PRESETS[preset][0]
    raw = P.panel(configure(spark), sf_dir, name)
    size = raw.agg((F.max("tick") + 1).alias("t"), (F.max("sensor_id") + 1).alias("n")).first()
    ticks, n = int(size["t"]), int(size["n"])
    start, count, lo, hi = FAULTS[preset]
    faults = I.schedule(ticks, n, int(ticks * start), count, lo, hi, kinds=I.KINDS if carrier else I.PLAIN)
    train, validation = start * 0.75, start * 0.25
    split = P.with_split(raw, train, validation)
    scaled = P.apply_minmax(split, P.fit_minmax(split))
    p = I.apply_faults(I.with_carrier(scaled) if carrier else scaled, I.fault_rows(spark, faults), n)
    return materialise(p), I.truth(spark, faults, ticks), faults, ticks, n, start


def config(preset: str, n: int, **change) -> ModelConfig:
    k = PRESETS[preset][3]
    base = {"n": n, "w": WINDOW.get(preset, 10), "k": k} | LIGHT | change
    return ModelConfig(**base).capped()


def fitted_forecast(p: DataFrame, cfg: ModelConfig, start: float, epochs: int = EPOCHS) -> tuple[DataFrame, dict]:
    """Train on the normal part, then score the whole panel in blocks; the forecast keeps its split."""
    x = T.matrix(p)
    a, b = int(len(x) * start * 0.75), int(len(x) * start)
    params, _ = T.fit(x, a, b - a, cfg, epochs=epochs, lr=RATE)
    vectors = P.to_vectors(p)
    f = T.score_blocks(vectors.select("tick", "x"), params, cfg)
    return f.join(p.select("tick", "sensor_id", "split"), ["tick", "sensor_id"]), params


def judged(flags: DataFrame, truth: DataFrame, adjusted: bool, by: list[str] | None = None) -> DataFrame:
    """Raw and, where asked, segment-adjusted measures of (by, tick, flag)."""
    rows = flags.join(truth, "tick").select(*(by or []), "tick", "y", "flag")
    out = N.prf(N.confusion(rows, by)).withColumn("adjusted", F.lit(False))
    if adjusted:
        out = out.unionByName(N.prf(N.confusion(N.adjust_segments(rows, by), by)).withColumn("adjusted", F.lit(True)))
    return out


def _measures(df: DataFrame, *keys: str) -> DataFrame:
    return df.select(*keys, "adjusted", "tp", "fp", "fn", "tn", *[F.round(c, 4).alias(c) for c in ("precision", "recall", "f1")])


def accuracy(spark: SparkSession, sf_dir: str, preset: str, seeds: int = 5, carrier: bool = True, **change) -> DataFrame:
    """Proposed model on one set: mean and deviation of the measures over seeds, each trained in a task of its own."""
    p, truth, _, _, n, start = injected(spark, sf_dir, preset, carrier)
    x = T.matrix(p)
    a, b = int(len(x) * start * 0.75), int(len(x) * start)

    def run(x, seed):
        cfg = config(preset, n, seed=seed, **change)
        params, _ = T.fit(x, a, b - a, cfg, epochs=EPOCHS, lr=RATE)
        _, win, y = T.windows(x, cfg.w)
        dev = np.concatenate([np.zeros((cfg.w, x.shape[1])), np.abs(T.predict(win, params, cfg) - y)])
        return str(seed), detect_rows(dev, a, b - a, first=cfg.w), b

    flags = materialise(fan_out(spark, x, list(range(1, seeds + 1)), run))
    runs = judged(flags, truth, PRESETS[preset][4], ["model"])
    columns = ["precision", "recall", "f1"]
    mean = N.mean_runs(runs, ["adjusted"], columns)
    return mean.select(F.lit(preset).alias("workload"), F.lit(seeds).alias("seeds"), "adjusted", *[F.round(c, 4).alias(c) for c in [*columns, *(f"sd_{c}" for c in columns)]])


def fan_out(spark: SparkSession, x: np.ndarray, jobs: list[tuple], run) -> DataFrame:
    """One row per job, each run in a task of its own on the shared matrix; ``run`` yields flag rows."""
    ship(spark)
    held = spark.sparkContext.broadcast((x, jobs))

    def work(frames):
        keep_freed()
        x, jobs = held.value
        for f in frames:
            for j in f["job"]:
                name, flag, first = run(x, jobs[int(j)])
                yield pd.DataFrame({"model": name, "tick": np.arange(first, len(flag)), "flag": flag[first:]})

    ids = spark.range(len(jobs)).withColumnRenamed("id", "job").repartitionByRange(len(jobs), "job")
    return ids.mapInPandas(work, "model string, tick long, flag int")


def leaderboard(spark: SparkSession, sf_dir: str, preset: str, names: list[str] | None = None) -> DataFrame:
    """All comparison detectors and the proposed model on one set, ranked by F1."""
    p, truth, _, ticks, n, start = injected(spark, sf_dir, preset)
    x = T.matrix(p)
    a, b = int(ticks * start * 0.75), int(ticks * start)
    cfg = config(preset, n)

    def run(x, name):
        if name == "proposed":
            params, _ = T.fit(x, a, b - a, cfg, epochs=EPOCHS, lr=RATE)
            at, win, y = T.windows(x, cfg.w)
            dev = np.concatenate([np.zeros((cfg.w, x.shape[1])), np.abs(T.predict(win, params, cfg) - y)])
        else:
            dev = B.DETECTORS[name][0](x, a, 1)
        return name, detect_rows(dev, a, b - a, first=cfg.w), b

    # the longest first, so that the others run beside them
    jobs = sorted([*(names or B.DETECTORS), "proposed"], key=lambda m: LONGEST.index(m) if m in LONGEST else len(LONGEST))
    flags = materialise(fan_out(spark, x, jobs, run))
    got = judged(flags, truth, PRESETS[preset][4], ["model"]).withColumn("workload", F.lit(preset))
    ranked = N.leaderboard(got, ["workload", "adjusted"], "f1")
    return _measures(ranked.withColumn("place", F.col("place").cast("int")), "workload", "model", "place", "best", "second")


def ablation(spark: SparkSession, sf_dir: str, preset: str, names: list[str] | None = None) -> DataFrame:
    """The nine variants beside the full model on one set, with the relative drop of precision."""
    p, truth, _, ticks, n, start = injected(spark, sf_dir, preset)
    x = T.matrix(p)
    a, b = int(ticks * start * 0.75), int(ticks * start)
    base = config(preset, n)

    def run(x, name):
        cfg = replace(base, **ABLATIONS.get(name, {})).capped()
        params, _ = T.fit(x, a, b - a, cfg, epochs=EPOCHS, lr=RATE)
        at, win, y = T.windows(x, cfg.w)
        dev = np.concatenate([np.zeros((cfg.w, x.shape[1])), np.abs(T.predict(win, params, cfg) - y)])
        return name, detect_rows(dev, a, b - a, first=cfg.w), b

    flags = materialise(fan_out(spark, x, ["proposed", *(names or ABLATIONS)], run))
    got = materialise(judged(flags, truth, PRESETS[preset][4], ["model"]))
    full = got.where("model = 'proposed'").select("adjusted", F.col("precision").alias("base"))
    out = N.relative_gain(got.join(full, "adjusted"), "base", "precision", "drop").withColumn("workload", F.lit(preset))
    return _measures(out.withColumn("drop", F.round("drop", 4)), "workload", "model", "drop")


def fault_rates(spark: SparkSession, sf_dir: str, programmes: int = 20, models: tuple[str, ...] = RIVALS) -> DataFrame:
    """Detected share of each of 20 faults.  A method is trained once, in a task of its own, and scores
    the clean ticks, then every programme's faulty ticks behind ``LEAD`` clean ones."""
    name = PRESETS["simulator"][0]
    raw = P.panel(configure(spark), sf_dir, name)
    split = P.with_split(raw)
    clean = materialise(I.with_carrier(P.apply_minmax(split, P.fit_minmax(split))))
    base = T.matrix(clean)
    ticks, n = base.shape
    a, b, active = int(ticks * 0.6), int(ticks * 0.8), int(ticks * 0.9)
    plans = [I.Fault(q, (7 * q + 3) % n, active, ticks - 1, I.KINDS[q % 10], I.SIZES[(3 * q + q // 10) % 4], (q // 10) % 2 == 1) for q in range(programmes)]
    last = materialise(clean.where(F.col("tick") >= active))
    faulty = [T.matrix(I.apply_faults(last, I.fault_rows(spark, [f]), n)) for f in plans]
    lead = min(LEAD, active)
    x = np.concatenate([base[:active], *(np.concatenate([base[active - lead : active], f]) for f in faulty)])
    cfg = config("simulator", n)
    ship(spark)
    held = spark.sparkContext.broadcast((x, ["proposed", *models]))

    def work(frames):
        x, names = held.value
        for f in frames:
            for j in f["job"]:
                name = names[int(j)]
                if name == "proposed":
                    params, _ = T.fit(x[:b], a, b - a, cfg, epochs=EPOCHS, lr=RATE)
                    _, win, y = T.windows(x, cfg.w)
                    dev = np.concatenate([np.zeros((cfg.w, n)), np.abs(T.predict(win, params, cfg) - y)])
                else:
                    dev = B.DETECTORS[name][0](x, a, 1)
                flag = detect_rows(dev, a, b - a, first=cfg.w)
                for q in range(programmes):
                    at = active + q * (lead + ticks - active) + lead
                    own = np.concatenate([flag[b:active], flag[at : at + ticks - active]])
                    yield pd.DataFrame({"model": name, "fault_id": q, "tick": np.arange(b, ticks), "flag": own})

    ids = spark.range(1 + len(models)).withColumnRenamed("id", "job").repartitionByRange(1 + len(models), "job")
    rows = ids.mapInPandas(work, "model string, fault_id int, tick long, flag int")
    rate = F.avg(F.when(F.col("tick") >= active, 100.0 * F.col("flag")))
    alarm = F.avg(F.when(F.col("tick") < active, 100.0 * F.col("flag")))
    return rows.groupBy("model", "fault_id").agg(F.round(rate, 4).alias("fdr"), F.round(alarm, 4).alias("false_alarm"))


def wk_sweep(spark: SparkSession, sf_dir: str, preset: str = "telemetry25", ws: tuple[int, ...] = (25, 30, 60), ks: tuple[int, ...] = (7, 10, 15, 20, 25)) -> DataFrame:
    """Window length and neighbours: every pair is trained in a task of its own; ``mse`` is of the validation forecasts."""
    p, truth, _, ticks, n, start = injected(spark, sf_dir, preset)
    x = T.matrix(p)
    a, b = int(ticks * start * 0.75), int(ticks * start)

    def run(x, job):
        w, k = job
        cfg = config(preset, n, w=w, k=k)
        params, _ = T.fit(x, a, b - a, cfg, epochs=EPOCHS, lr=RATE)
        at, win, y = T.windows(x, w)
        dev = np.concatenate([np.zeros((w, n)), np.abs(T.predict(win, params, cfg) - y)])
        mse = float((dev[max(a, w) : b] ** 2).mean())
        return f"{w}/{k}/{mse!r}", detect_rows(dev, a, b - a, first=w), b

    flags = fan_out(spark, x, [(w, k) for w in ws for k in ks], run)
    got = judged(flags, truth, False, ["model"])
    parts = F.split("model", "/")
    return got.select(parts[0].cast("int").alias("w"), parts[1].cast("int").alias("k"), F.round(parts[2].cast("double"), 6).alias("mse"), *[F.round(c, 4).alias(c) for c in ("precision", "recall", "f1")])


def diagnosis(spark: SparkSession, sf_dir: str, preset: str = "telemetry25", horizon: int = 3, hops: int = 2) -> DataFrame:
    """From the flags of a trained model to advice, one row for each incident (a run of flagged ticks):
    its root at the first tick, how many sensors the trace reaches, the most salient of them with its
    hop and the sign of its correlation, and values of the root for the next ``horizon`` ticks."""
    p, _, _, _, n, start = injected(spark, sf_dir, preset)
    cfg = config(preset, n)
    forecast, params = fitted_forecast(p, cfg, start)
    score, ticks, threshold = V.detect(materialise(forecast))
    score = materialise(score)
    flags = V.flag(ticks, threshold)
    before = flags.select((F.col("tick") + 1).alias("tick"), F.col("flag").alias("was"))
    onset = flags.join(before, "tick", "left").where("flag = 1 AND coalesce(was, 0) = 0")
    found = materialise(G.root(score, onset))
    nodes = spark.createDataFrame([(i, [float(v) for v in z]) for i, z in enumerate(params["z"])], "sensor_id int, z array<double>")
    members = materialise(S.build(nodes, k=cfg.k))
    trace = materialise(G.propagate(members, found, hops))
    reached = trace.groupBy("root").agg(F.count("*").alias("reached"))
    near = p.join(found.select(F.explode(F.sequence(F.col("tick") - cfg.w, "tick")).alias("tick")).distinct(), "tick", "left_semi")
    win = W.lagged(near, cfg.w).join(found.select("tick"), "tick", "left_semi")
    attention = FW.convolve(FW.with_position(win, params, cfg, members), members, params, cfg).member_attention
    at_onset = score.join(found.select("tick"), "tick", "left_semi")
    first = G.salient(trace, attention, at_onset, 1).select("root", F.col("to_id").alias("salient"), "hop")
    signs = G.evidence(forecast, trace, p, 0, now=False).select("root", F.col("sensor_id").alias("salient"), "sign").distinct()
    steps = [(r["tick"], r["root"], r["score"]) for r in found.orderBy("tick").collect()]
    if not steps:
        advice = spark.createDataFrame([], "tick long, recommended array<double>, before double, after double")
    else:
        x = T.matrix(p)
        stats = V.fit_robust(V.abs_error(forecast)).orderBy("sensor_id").collect()
        med, iqr = (np.array([r[c] for r in stats]) for c in ("med", "iqr"))
        padded = np.concatenate([x, np.repeat(x[-1:], horizon, 0)])
        contexts = [C.Context(params, cfg, x[t - cfg.w : t], padded[t : t + horizon], med, iqr, root) for t, root, _ in steps]
        incident = spark.createDataFrame([(i, t) for i, (t, _, _) in enumerate(steps)], "incident long, tick long")
        advice = C.search_many(spark, contexts, horizon, "score", C.Search(generations=20)).join(incident, "incident")
    rows = found.join(reached, "root", "left").join(first, "root", "left").join(signs, ["root", "salient"], "left").join(advice, "tick")
    rounded = [F.round(c, 4).alias(c) for c in ("score", "before", "after")]
    return rows.select("tick", "root", "reached", "salient", "hop", "sign", F.transform("recommended", lambda v: F.round(v, 4)).alias("recommended"), *rounded)


def forecast_vs_truth(spark: SparkSession, sf_dir: str, preset: str = "telemetry25", sensors: tuple[int, ...] | None = None) -> DataFrame:
    p, _, _, _, n, start = injected(spark, sf_dir, preset)
    f, _ = fitted_forecast(p, config(preset, n), start)
    _, ticks, threshold = V.detect(f)
    flags = V.flag(ticks, threshold).select("tick", "flag")
    rows = f.where(F.col("sensor_id").isin(*sensors)) if sensors else f
    return rows.join(flags, "tick", "left").select("tick", "sensor_id", F.round("y", 6).alias("y"), F.round("y_hat", 6).alias("y_hat"), "flag")


def case_study(spark: SparkSession, sf_dir: str) -> dict:
    """Actuator and meter that move together: the actuator sticks while the meter goes on rising."""
    raw = P.panel(configure(spark), sf_dir, "event_meter")
    split = P.with_split(raw)
    x = T.matrix(I.with_carrier(P.apply_minmax(split, P.fit_minmax(split))))
    ticks, n = x.shape
    a, b = int(ticks * 0.6), int(ticks * 0.8)
    actuator, meter = 0, 1  # click|count, click|sum
    # the meter follows its actuator; then, at a trough, the actuator sticks for 12 ticks
    x[:, meter] = 0.8 * x[:, actuator] + 0.1
    t0 = (b + (ticks - b) // 2) // 12 * 12 + 9
    x[t0 : t0 + 12, actuator] = x[t0 - 1, actuator]
    cfg = ModelConfig(n=n, w=10, k=3, d=8)
    params, _ = T.fit(x, a, b - a, cfg, epochs=25, lr=RATE)
    at, win, y = T.windows(x, cfg.w)
    dev = np.abs(T.predict(win, params, cfg) - y)
    val = (at >= a) & (at < b)
    q1, med, q3 = np.percentile(dev[val], [25, 50, 75], axis=0)
    return {"x": x, "cfg": cfg, "params": params, "dev": dev, "at": at, "med": med, "iqr": q3 - q1, "actuator": actuator, "meter": meter, "t0": t0, "split": (a, b)}


def case_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Root of the deviation, hops to the meter and the recommended action of the case study."""
    c = case_study(spark, sf_dir)
    score = (c["dev"] - c["med"]) / np.maximum(c["iqr"], 1e-6)
    inside = (c["at"] >= c["t0"]) & (c["at"] < c["t0"] + 6)
    root = int(score[inside].max(0).argmax())
    nodes = spark.createDataFrame([(i, [float(v) for v in z]) for i, z in enumerate(c["params"]["z"])], "sensor_id int, z array<double>")
    members = materialise(S.build(nodes, k=c["cfg"].k))
    trace = G.propagate(members, spark.createDataFrame([(root,)], "root int"), 3)
    other = c["meter"] if root == c["actuator"] else c["actuator"]
    hop = trace.where(F.col("to_id") == other).agg(F.min("hop").alias("hop"))
    ctx = context(c, c["actuator"])
    found = C.search_many(spark, [ctx], 1, "score", C.Search(generations=20))
    return found.crossJoin(hop).select(F.lit(root).alias("root"), F.col("hop").alias("hops_to_partner"), "sensor", F.round("current", 4).alias("current"), F.round(F.col("recommended")[0], 4).alias("recommended"), F.round("before", 4).alias("before"), F.round("after", 4).alias("after"))


def context(c: dict, sensor: int, horizon: int = 1) -> C.Context:
    t = c["t0"] + 4
    return C.Context(c["params"], c["cfg"], c["x"][t - c["cfg"].w : t], c["x"][t : t + horizon], c["med"], c["iqr"], sensor)


def control_search(spark: SparkSession, sf_dir: str, horizons: tuple[int, ...] = (1, 2)) -> DataFrame:
    """Genetic search against the grid on the case study, for both objectives and over one and two ticks."""
    c = case_study(spark, sf_dir)
    rows = []
    for horizon in horizons:
        ctx = context(c, c["actuator"], horizon)
        for objective in ("score", "tracking"):
            best, loss, history = C.search(ctx, horizon, objective, C.Search(generations=20 * horizon))
            g, g_loss = C.grid(ctx, horizon, 41, objective)
            rows.append((objective, horizon, [round(float(v), 3) for v in best], round(loss, 5), [round(float(v), 3) for v in g], round(g_loss, 5), len(history)))
    return spark.createDataFrame(rows, "objective string, horizon int, found array<double>, found_loss double, grid array<double>, grid_loss double, generations int")
