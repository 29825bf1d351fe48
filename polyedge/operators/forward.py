"""The forward path as relational expressions, one row per (tick, node) or (tick, edge).

All steps are keyed by tick first, so one exchange on tick serves the whole pass; memberships,
embeddings and weights are bounded by the sensor list and travel as broadcasts or literals.  This
path is for small widths and as the oracle of the block path; wide models run in numpy blocks.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, Window, functions as F

from polyedge.functions import algebra as A
from polyedge.models.config import ModelConfig

Params = dict[str, np.ndarray]


@dataclass
class Convolved:
    nodes: DataFrame  # tick, sensor_id, z, u, x
    edges: DataFrame  # tick, edge_id, e, m
    member_attention: DataFrame  # tick, edge_id, sensor_id, coef
    edge_attention: DataFrame


def with_position(win: DataFrame, params: Params, cfg: ModelConfig, members: DataFrame | None = None) -> DataFrame:
    """Add the positional row of each sensor to its window."""
    p = positions(params, cfg)
    if p is None:
        return win
    if cfg.position == "neighbourhood":
        p = neighbourhood_mean(p, members)
    rows = win.sparkSession.createDataFrame([(i, [float(x) for x in r]) for i, r in enumerate(p)], "sensor_id int, __p array<double>")
    return win.join(F.broadcast(rows), "sensor_id").withColumn("win", A.add(F.col("win"), F.col("__p"))).drop("__p")


def positions(params: Params, cfg: ModelConfig) -> np.ndarray | None:
    if cfg.position == "none":
        return None
    if cfg.position == "sinusoidal":
        return sinusoidal(cfg.n, cfg.w)
    return params["pos"]


def sinusoidal(n: int, w: int, base: float = 10_000.0) -> np.ndarray:
    i, j = np.arange(n)[:, None], np.arange(w)
    angle = i / base ** (2 * (j // 2) / w)
    return np.where(j % 2 == 0, np.sin(angle), np.cos(angle))


def neighbourhood_mean(p: np.ndarray, members: DataFrame) -> np.ndarray:
    """Mean of a row, the mean over its local and the mean over its global neighbours (bounded by n)."""
    pairs = [(r["edge_id"], r["sensor_id"]) for r in members.select("edge_id", "sensor_id").distinct().collect()]
    out = p.copy()
    for i in range(len(p)):
        local = [s for e, s in pairs if e == i and s != i] or [i]
        glob = [e for e, s in pairs if s == i] or [i]
        out[i] = (p[i] + p[local].mean(0) + p[glob].mean(0)) / 3
    return out


def z_rows(df: DataFrame, params: Params) -> DataFrame:
    z = df.sparkSession.createDataFrame([(i, [float(x) for x in r]) for i, r in enumerate(params["z"])], "sensor_id int, z array<double>")
    return df.join(F.broadcast(z), "sensor_id")


def _score(vec: np.ndarray, parts: list[Column]) -> Column:
    """Dot of a weight vector with a concatenation, slice by slice."""
    flat, at, out = vec.ravel(), 0, F.lit(0.0)
    step = len(flat) // len(parts)
    for p in parts:
        out = out + A.dot(A.vector(flat[at : at + step]), p)
        at += step
    return out


def _coef(df: DataFrame, keys: list[str], score: str, name: str, cfg: ModelConfig) -> DataFrame:
    return A.softmax_by(df, keys, score, name) if cfg.attention else df.withColumn(name, F.lit(1.0))


def convolve(win: DataFrame, members: DataFrame, params: Params, cfg: ModelConfig) -> Convolved:
    """Group convolution: windows to node features by way of edges.

    The member score belongs to the node alone, and the edge score is a node part plus an edge
    part, so neither needs wide arrays on the membership rows.
    """
    d = cfg.d
    n = z_rows(win, params)
    n = n.withColumn("u", A.matvec(params["w_in"], F.col("win"))).withColumn("h", A.matvec(params["w_self"], F.col("win")))
    own = [F.col("z"), F.col("u")] if cfg.use_z else [F.col("u")]
    flat = params["a_edge"].ravel()
    n = n.withColumn("a", A.relu(_score(params["a_member"], own))).withColumn("b_node", _score(flat[: len(own) * d], own))
    n = n.repartition("tick").select("tick", "sensor_id", "z", "u", "h", "a", "b_node")
    on = n.select("tick", "sensor_id", "u", "a", "b_node").join(F.broadcast(members), "sensor_id")
    alpha = _coef(on, ["tick", "edge_id"], "a", "coef", cfg)
    edges = alpha.groupBy("tick", "edge_id").agg(A.sum_vectors("u", d, F.col("coef")).alias("s")).withColumn("e", A.sigmoid_vec(F.col("s")))
    edges = edges.withColumn("m", A.matvec(params["w_edge"], F.col("e"))).withColumn("b_edge", A.dot(A.vector(flat[-d:]), F.col("m"))).select("tick", "edge_id", "e", "m", "b_edge")
    back = on.select("tick", "edge_id", "sensor_id", "b_node").join(edges, ["tick", "edge_id"]).withColumn("b", A.relu(F.col("b_node") + F.col("b_edge")))
    beta = _coef(back, ["tick", "sensor_id"], "b", "coef", cfg)
    got = beta.groupBy("tick", "sensor_id").agg(A.sum_vectors("m", d, F.col("coef")).alias("g"))
    nodes = n.join(got, ["tick", "sensor_id"], "left").withColumn("x", A.relu_vec(A.add(F.col("h"), F.coalesce("g", A.vector([0.0] * d)))))
    return Convolved(nodes.select("tick", "sensor_id", "z", "u", "x"), edges.select("tick", "edge_id", "e", "m"), alpha.select("tick", "edge_id", "sensor_id", "coef"), beta.select("tick", "edge_id", "sensor_id", "coef"))


@dataclass
class Pooled:
    kept: DataFrame  # tick, sensor_id, score, rank
    members: DataFrame  # tick, edge_id, sensor_id
    nodes: DataFrame  # tick, sensor_id, x


def importance(nodes: DataFrame, params: Params, cfg: ModelConfig) -> DataFrame:
    theta = params["theta"].ravel()
    if cfg.score == "projection":
        return nodes.withColumn("score", A.dot(A.vector(theta / np.linalg.norm(theta)), F.col("x")))
    return A.softmax_by(nodes.withColumn("__t", A.dot(A.vector(theta), F.col("x"))), ["tick"], "__t", "score").drop("__t")


def top_nodes(scored: DataFrame, n: int, ratio: float) -> DataFrame:
    """The best ceil(ratio n) nodes of each tick, ties by id."""
    w = Window.partitionBy("tick").orderBy(F.desc("score"), "sensor_id")
    keep = max(1, int(np.ceil(ratio * n - 1e-9)))
    return scored.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= keep)


def induce(members: DataFrame, kept: DataFrame) -> DataFrame:
    """Edges whose centre is kept, with their kept members; every edge still has its centre."""
    k = kept.select("tick", "sensor_id")
    on = k.join(F.broadcast(members), "sensor_id")
    return on.join(k.select("tick", F.col("sensor_id").alias("edge_id")), ["tick", "edge_id"], "left_semi").select("tick", "edge_id", "sensor_id")


def pool(c: Convolved, members: DataFrame, params: Params, cfg: ModelConfig) -> Pooled:
    d = cfg.d
    scored = importance(c.nodes, params, cfg)
    kept = top_nodes(scored, cfg.n, cfg.ratio)
    sub = induce(members, kept)
    gate = A.scale(F.col("x"), A.relu(F.col("score"))) if cfg.gate else F.col("x")
    n = kept.withColumn("v", A.matvec(params["p_node"], gate))
    flat = params["a_pool"].ravel()
    own = [F.col("z"), F.col("v")] if cfg.use_z else [F.col("v")]
    n = n.withColumn("k_node", _score(flat[: len(own) * d], own)).select("tick", "sensor_id", "v", "k_node")
    on = sub.join(n, ["tick", "sensor_id"])
    edges = on.groupBy("tick", "edge_id").agg(A.sum_vectors("v", d).alias("s")).withColumn("m", A.matvec(params["p_edge"], A.sigmoid_vec(F.col("s"))))
    edges = edges.withColumn("k_edge", A.dot(A.vector(flat[-d:]), F.col("m"))).select("tick", "edge_id", "m", "k_edge")
    back = on.select("tick", "edge_id", "sensor_id", "k_node").join(edges, ["tick", "edge_id"]).withColumn("k", A.relu(F.col("k_node") + F.col("k_edge")))
    zeta = _coef(back, ["tick", "sensor_id"], "k", "coef", cfg)
    got = zeta.groupBy("tick", "sensor_id").agg(A.sum_vectors("m", d, F.col("coef")).alias("g"))
    out = n.join(got, ["tick", "sensor_id"]).select("tick", "sensor_id", A.sigmoid_vec(A.add(F.col("v"), F.col("g"))).alias("x"))
    return Pooled(kept.select("tick", "sensor_id", "score", F.col("rank").cast("int").alias("rank")), sub, out)


def scatter(pooled: DataFrame, nodes: DataFrame, d: int) -> DataFrame:
    """Pooled rows back on all nodes, zero vectors elsewhere."""
    return nodes.select("tick", "sensor_id").join(pooled, ["tick", "sensor_id"], "left").withColumn("x", F.coalesce("x", A.vector([0.0] * d)))


def with_skip(c: Convolved, pooled: DataFrame, cfg: ModelConfig) -> DataFrame:
    up = pooled.select("tick", "sensor_id", F.col("x").alias("up"))
    both = c.nodes.join(up, ["tick", "sensor_id"], "left")
    zero = A.vector([0.0] * cfg.d)
    x = {"add": A.add(F.coalesce("up", zero), F.col("x")), "fill": F.coalesce("up", "x"), "none": F.coalesce("up", zero)}[cfg.skip]
    return both.select("tick", "sensor_id", "z", x.alias("y"))


@dataclass
class Refined:
    nodes: DataFrame  # tick, sensor_id, z, x
    attention: DataFrame  # tick, edge_id, sensor_id, coef


def refine(c: Convolved, p: Pooled, members: DataFrame, params: Params, cfg: ModelConfig) -> Refined:
    """Unpool with skip connection, then attention over edges by the time-shift score.

    The score of node i and edge p, (S(g_p - g_i)).(S(g_p + g_i)), is |S g_p|^2 - |S g_i|^2; within
    a node's softmax its own term cancels.  With ``rewrites`` only the edge term is computed.
    """
    d = cfg.d
    n = with_skip(c, p.nodes, cfg).withColumn("v", A.matvec(params["u_node"], F.col("y")))
    mixed = F.concat("z", "v") if cfg.use_z else F.col("v")
    shift = params["u_shift"]
    factored = cfg.shift == "difference" and cfg.rewrites
    if not factored:
        n = n.withColumn("sg", A.matvec(shift, A.matvec(params["u_mix"], mixed)))
    on = n.join(F.broadcast(members), "sensor_id")
    edges = on.groupBy("tick", "edge_id").agg(A.sum_vectors("v", d).alias("s")).withColumn("m", A.matvec(params["u_edge"], A.sigmoid_vec(F.col("s"))))
    edges = edges.withColumn("sm", A.matvec(shift, F.col("m"))).select("tick", "edge_id", "m", "sm")
    back = on.select("tick", "edge_id", "sensor_id", *([] if factored else ["sg"])).join(edges, ["tick", "edge_id"])
    if factored:
        delta = A.dot(F.col("sm"), F.col("sm"))
    elif cfg.shift == "dot":
        delta = A.dot(F.col("sg"), F.col("sm"))
    else:
        delta = A.dot(A.sub(F.col("sm"), F.col("sg")), A.add(F.col("sm"), F.col("sg")))
    gamma = _coef(back.withColumn("delta", delta), ["tick", "sensor_id"], "delta", "coef", cfg)
    got = gamma.groupBy("tick", "sensor_id").agg(A.sum_vectors("m", d, F.col("coef")).alias("g"))
    out = n.join(got, ["tick", "sensor_id"], "left").select("tick", "sensor_id", "z", A.add(F.col("v"), F.coalesce("g", A.vector([0.0] * d))).alias("x"))
    return Refined(out, gamma.select("tick", "edge_id", "sensor_id", "coef"))


def _flat(r: Refined) -> DataFrame:
    return r.nodes.select("tick", "sensor_id", A.hadamard(F.col("z"), F.col("x")).alias("zx"))


def forecast(r: Refined, params: Params, cfg: ModelConfig) -> DataFrame:
    """(tick, sensor_id, y_hat): one linear map of all embedded node features of the tick."""
    d, w = cfg.d, params["head_w"]
    blocks = [(j, [[float(x) for x in w[i, j * d : (j + 1) * d]] for i in range(cfg.n)]) for j in range(cfg.n)]
    rows = r.nodes.sparkSession.createDataFrame(blocks, "sensor_id int, hw array<array<double>>")
    parts = _flat(r).join(F.broadcast(rows), "sensor_id").select("tick", F.posexplode(F.transform("hw", lambda h: A.dot(h, F.col("zx")))).alias("target", "part"))
    bias = params.get("head_b")
    add = F.col("s") if bias is None else F.col("s") + F.get(A.vector(bias), F.col("target"))
    return parts.groupBy("tick", "target").agg(F.sum("part").alias("s")).select("tick", F.col("target").alias("sensor_id"), add.alias("y_hat"))


def classify(r: Refined, params: Params, cfg: ModelConfig) -> DataFrame:
    """(tick, p): probability that the tick is anomalous."""
    w = params["cls_w"].reshape(cfg.n, cfg.d)
    rows = r.nodes.sparkSession.createDataFrame([(j, [float(x) for x in w[j]]) for j in range(cfg.n)], "sensor_id int, cw array<double>")
    s = _flat(r).join(F.broadcast(rows), "sensor_id").groupBy("tick").agg(F.sum(A.dot(F.col("cw"), F.col("zx"))).alias("s"))
    bias = float(params["cls_b"][0]) if "cls_b" in params else 0.0
    return s.select("tick", A.sigmoid(F.col("s") + F.lit(bias)).alias("p"))


def encode_decode(win: DataFrame, members: DataFrame, params: Params, cfg: ModelConfig) -> Refined:
    """The whole single-stage encoder-decoder."""
    c = convolve(with_position(win, params, cfg, members), members, params, cfg)
    return refine(c, pool(c, members, params, cfg), members, params, cfg)
