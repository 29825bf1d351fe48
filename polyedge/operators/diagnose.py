"""Root cause: from the sensor that deviates most along the learned groups, layer by layer."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from polyedge.session import materialise


def root(score: DataFrame, flags: DataFrame) -> DataFrame:
    """(tick, root, score) of flagged ticks; ties go to the smallest sensor."""
    best = F.max(F.struct("score", (-F.col("sensor_id")).alias("neg")))
    hit = score.join(flags.where("flag = 1").select("tick"), "tick", "left_semi")
    return hit.groupBy("tick").agg(best.alias("b")).select("tick", (-F.col("b.neg")).alias("root"), F.col("b.score").alias("score"))


def propagate(members: DataFrame, roots: DataFrame, hops: int | None = None, cut_every: int = 3) -> DataFrame:
    """Computation hypergraph: (root, hop, edge_id, from_id, to_id), each node reached once per root.

    A hop goes from a reached node, by every edge that holds it, to the members not reached before;
    of several ways in, the one by the smallest edge and sender stays.  Without ``hops`` it runs to
    the fixed point.  Spark broadcasts the members if their size is
    under the session's bound.
    """
    m = materialise(members.select("edge_id", "sensor_id").distinct())
    into = m.select("edge_id", F.col("sensor_id").alias("from_id"))
    out_of = m.select("edge_id", F.col("sensor_id").alias("to_id"))
    seen = roots.select("root", F.col("root").alias("node")).distinct()
    front, layers, hop = seen, [], 0
    while hops is None or hop < hops:
        hop += 1
        step = front.join(into, front.node == F.col("from_id")).join(out_of, "edge_id").select("root", "edge_id", "from_id", "to_id")
        new = step.join(seen.select("root", F.col("node").alias("to_id")), ["root", "to_id"], "left_anti")
        first = new.groupBy("root", "to_id").agg(F.min(F.struct("edge_id", "from_id")).alias("w"))
        layer = first.select("root", F.lit(hop).alias("hop"), F.col("w.edge_id").alias("edge_id"), F.col("w.from_id").alias("from_id"), "to_id")
        if hops is None or hop % cut_every == 0:
            layer = materialise(layer)
        if hops is None and layer.isEmpty():
            break
        layers.append(layer)
        front = layer.select("root", F.col("to_id").alias("node"))
        seen = seen.unionByName(front)
    if not layers:
        return roots.sparkSession.createDataFrame([], "root int, hop int, edge_id int, from_id int, to_id int")
    out = layers[0]
    for x in layers[1:]:
        out = out.unionByName(x)
    return out


def salient(trace: DataFrame, attention: DataFrame, scores: DataFrame, top: int) -> DataFrame:
    """The ``top`` trace steps of each root by attention times the score of the node reached."""
    w = Window.partitionBy("root").orderBy(F.desc("weight"), "hop", "edge_id", "to_id")
    a = attention.groupBy("edge_id", F.col("sensor_id").alias("to_id")).agg(F.avg("coef").alias("coef"))
    s = scores.groupBy(F.col("sensor_id").alias("to_id")).agg(F.max("score").alias("score"))
    ranked = trace.join(a, ["edge_id", "to_id"], "left").join(s, "to_id", "left")
    ranked = ranked.withColumn("weight", F.coalesce("coef", F.lit(0.0)) * F.coalesce("score", F.lit(0.0)))
    return ranked.withColumn("place", F.row_number().over(w)).where(F.col("place") <= top)


def evidence(forecast: DataFrame, trace: DataFrame, panel: DataFrame, tick: int, now: bool = True) -> DataFrame:
    """Observed and predicted values of the root and its trace at one tick, with the sign of each
    node's correlation with the root over the training rows.  Without ``now`` only the signs."""
    nodes = trace.select("root", F.col("to_id").alias("sensor_id"), "hop").unionByName(trace.select("root", F.col("root").alias("sensor_id"), F.lit(0).alias("hop")).distinct())
    train = panel.where("split = 'train'") if "split" in panel.columns else panel
    x, y = train.select("tick", "sensor_id", "value"), train.select("tick", F.col("sensor_id").alias("root"), F.col("value").alias("rv"))
    c = nodes.join(x, "sensor_id").join(y, ["tick", "root"]).groupBy("root", "sensor_id").agg(F.signum(F.corr("value", "rv")).alias("sign"))
    if not now:
        return nodes.join(c, ["root", "sensor_id"], "left").select("root", "hop", "sensor_id", "sign")
    seen = forecast.where(F.col("tick") == tick).select("sensor_id", "y", "y_hat")
    return nodes.join(seen, "sensor_id").join(c, ["root", "sensor_id"], "left").select("root", "hop", "sensor_id", "y", "y_hat", "sign")
