"""Toxicity: linear classifier over hashed character n-grams scaled by naive Bayes log-count ratios.

Presence of a lower-cased character n-gram (3 to 6 code points, word edges kept as spaces) is one
binary feature.  On labelled texts each bucket gets the smoothed log ratio of its share among
toxic and among clean documents; a sparse logistic regression is fitted to the scaled features.
Only buckets with a weight are looked up at scoring time, so a text costs one vector pass.

Defined results: null and empty texts have no features and get the bias alone; without both
classes among the labelled rows the score is the share of label 1 (``default_score`` if none).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F, types as T

from polyedge.llm import common
from polyedge.llm.quality import labelled_sample

ORDERS = (3, 4, 5, 6)
MIX = np.uint64(0x9E3779B97F4A7C15)


def gram_buckets(text: str, bits: int) -> list[np.ndarray]:
    """Bucket of every n-gram of one text, an array per order; edges of the text count as spaces."""
    c = np.frombuffer(f" {text.lower()} ".encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    c = np.where((c == 10) | (c == 9) | (c == 13), np.uint64(32), c)
    out, h = [], c * MIX
    for n in range(2, ORDERS[-1] + 1):
        if len(c) < n:
            break
        h = (h[:-1] ^ (h[:-1] >> np.uint64(29))) * MIX + c[n - 1 :]
        if n in ORDERS:
            out.append(((h ^ (h >> np.uint64(32))) * MIX >> np.uint64(64 - bits)).astype(np.int64))
    return out


@dataclass
class ToxicityModel:
    bits: int
    bias: float
    buckets: np.ndarray  # sorted, of non-zero weights
    weights: np.ndarray  # log-count ratio times regression weight

    def score_texts(self, texts: list[str]) -> np.ndarray:
        dense = np.zeros(1 << self.bits)
        dense[self.buckets] = self.weights
        used = np.zeros(1 << self.bits, bool)
        used[self.buckets] = True
        out = np.empty(len(texts))
        for i, t in enumerate(texts):
            hits = [g[used[g]] for g in gram_buckets(t, self.bits)]
            hit = np.unique(np.concatenate(hits)) if hits else np.empty(0, np.int64)
            out[i] = self.bias + dense[hit].sum()
        return 1 / (1 + np.exp(-np.clip(out, -35, 35)))


def log_count_ratios(pos: np.ndarray, neg: np.ndarray, n_pos: float, n_neg: float, smooth: float) -> np.ndarray:
    """Log of a bucket's smoothed share among toxic documents over that among clean ones."""
    return np.log((pos + smooth) / (n_pos + 2 * smooth)) - np.log((neg + smooth) / (n_neg + 2 * smooth))


def choose_buckets(pos: np.ndarray, neg: np.ndarray, ratio: np.ndarray, keep_buckets: int) -> np.ndarray:
    """The buckets whose ratio says most; one seen in under three documents says nothing about new ones."""
    strength = np.abs(ratio) * np.sqrt(pos + neg) * (pos + neg >= 3)
    chosen = np.sort(np.argsort(-strength, kind="stable")[:keep_buckets])
    return chosen[strength[chosen] > 0]


def fit_scaled(rows: list[np.ndarray], labels: np.ndarray, chosen: np.ndarray, ratio: np.ndarray, bits: int, l1: float = 2e-4, rounds: int = 250) -> ToxicityModel:
    """Sparse logistic regression on scaled features by accelerated proximal gradient.

    ``rows`` hold places in ``chosen``; ``ratio`` is that of the chosen buckets.
    """
    n_pos, n_neg = labels.sum(), len(labels) - labels.sum()
    row_of = np.repeat(np.arange(len(rows)), [len(c) for c in rows])
    col = np.concatenate(rows).astype(np.int64)
    val = ratio[col]
    weight = np.where(labels == 1, 0.5 / n_pos, 0.5 / n_neg)
    w, b = np.zeros(len(chosen)), 0.0
    # per-coordinate step from the diagonal bound of the curvature
    per_row = np.bincount(row_of, weights=np.abs(val), minlength=len(rows))
    bound = 0.25 * np.bincount(col, weights=weight[row_of] * np.abs(val) * (per_row[row_of] + 1), minlength=len(chosen)) + 1e-9
    bound_b = 0.25 * (weight * (per_row + 1)).sum()
    v, vb, t = w.copy(), b, 1.0
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(np.bincount(row_of, weights=val * v[col], minlength=len(rows)) + vb, -35, 35)))
        d = weight * (p - labels)
        g = np.bincount(col, weights=val * d[row_of], minlength=len(chosen))
        nw = v - g / bound
        nw = np.sign(nw) * np.maximum(np.abs(nw) - l1 / bound, 0)
        nb = vb - d.sum() / bound_b
        nt = (1 + np.sqrt(1 + 4 * t * t)) / 2
        v, vb = nw + (t - 1) / nt * (nw - w), nb + (t - 1) / nt * (nb - b)
        w, b, t = nw, nb, nt
    on = np.flatnonzero(w)
    return ToxicityModel(bits, float(b), chosen[on], w[on] * ratio[on])


def constant_model(labels: np.ndarray, bits: int, default_score: float) -> ToxicityModel:
    share = float(labels.mean()) if len(labels) else default_score
    share = min(max(share, 1e-6), 1 - 1e-6)
    return ToxicityModel(bits, float(np.log(share / (1 - share))), np.empty(0, np.int64), np.empty(0))


def _document_counts(batches: Iterator[pa.RecordBatch], bits: int) -> Iterator[pa.RecordBatch]:
    """Documents per bucket and label within one task."""
    count = np.zeros((2, 1 << bits), np.int64)
    for b in batches:
        for text, y in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
            if g := gram_buckets(text or "", bits):
                count[y, np.unique(np.concatenate(g))] += 1
    on = np.flatnonzero(count.any(0))
    yield pa.RecordBatch.from_arrays([pa.array(on), pa.array(count[1, on]), pa.array(count[0, on])], names=["bucket", "pos", "neg"])


def _places(texts: list[str], bits: int, chosen: np.ndarray) -> list[list[np.ndarray]]:
    place = np.full(1 << bits, -1, np.int32)
    place[chosen] = np.arange(len(chosen))
    out = []
    for t in texts:
        g = gram_buckets(t, bits)
        p = place[np.unique(np.concatenate(g))] if g else np.empty(0, np.int32)
        out.append(p[p >= 0])
    return [out]


def fit(docs: DataFrame, labels: DataFrame, label: str = "toxic", use: Column | None = None, bits: int = 18, max_rows: int = 6000, keep_buckets: int = 8000, smooth: float = 1.0, default_score: float = 0.5) -> ToxicityModel:
    """Fit on a bounded sample of labelled rows (``max_rows``); ``use`` filters rows by their id.

    Document counts per bucket are summed on the executors; the driver gets one row per bucket,
    then the rows of the sample over the chosen buckets only.
    """
    sample = common.cut(labelled_sample(docs, labels, label, use, max_rows)).coalesce(8)
    common.tidy(docs.sparkSession)
    sizes = {r[0]: r[1] for r in sample.groupBy("__label").count().collect()}
    n_pos, n_neg = sizes.get(1, 0), sizes.get(0, 0)
    if not n_pos or not n_neg:
        return constant_model(np.repeat([1.0, 0.0], [n_pos, n_neg]), bits, default_score)
    common.ship(docs.sparkSession)
    counts = sample.select("text", "__label").mapInArrow(partial(_document_counts, bits=bits), "bucket long, pos long, neg long").groupBy("bucket").agg(F.sum("pos").alias("pos"), F.sum("neg").alias("neg")).toPandas()
    pos, neg = np.zeros(1 << bits), np.zeros(1 << bits)
    pos[counts["bucket"]], neg[counts["bucket"]] = counts["pos"], counts["neg"]
    ratio = log_count_ratios(pos, neg, n_pos, n_neg, smooth)
    chosen = choose_buckets(pos, neg, ratio, keep_buckets)
    got = common.with_text_columns(sample, "text", partial(_places, bits=bits, chosen=chosen), [("b", T.ArrayType(T.IntegerType()))], keep=["__id", "__label"]).toPandas()
    got = got.sort_values(["__id", "__label"], kind="stable")
    return fit_scaled(list(got["b"]), got["__label"].to_numpy(dtype=float), chosen, ratio[chosen], bits)


def _scored(texts: list[str], model: ToxicityModel) -> list[np.ndarray]:
    s = model.score_texts(texts)
    return [s, (s >= 0.5).astype(np.int32)]


def score(docs: DataFrame, model: ToxicityModel, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Append ``score`` (double in 0..1) and ``predicted`` (int); every row is returned."""
    return common.with_text_columns(docs, text_col, partial(_scored, model=model), [("score", T.DoubleType()), ("predicted", T.IntegerType())], keep)
