"""Quality classifier: hashed word n-grams, logistic regression fitted by follow-the-regularised-leader.

A text becomes a stream of word and punctuation-run tokens; a token that repeats the one before
it becomes one fixed token, an all-capital word keeps a mark.  Unigrams and bigrams of that stream
are hashed into ``2**bits`` buckets; a bucket's value is the square root of its count over the
norm of the document, so the sparse dot product is bounded whatever the length of the text.

Defined results: a null or empty text has no features and gets the bias alone; a batch of labelled
rows without both classes gives a constant score (the share of label 1, or ``default_score`` with
no labelled row at all).  Rows with a null label are not used in fitting.
"""

from __future__ import annotations

import re
import zlib
from dataclasses import dataclass
from functools import partial

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, functions as F, types as T

from polyedge.llm import common

TOKEN = re.compile(r"\w+|[^\w\s]+")
SAME = 0x9E3779B1


def _token_hash(token: str) -> int:
    mark = "^" if len(token) > 1 and token.isupper() else ""
    return zlib.crc32((token.lower() + mark).encode("utf-8", "surrogatepass"))


def features(text: str, bits: int, memo: dict[str, int]) -> tuple[np.ndarray, np.ndarray]:
    """Bucket numbers and counts of one text."""
    tokens = TOKEN.findall(text)
    if not tokens:
        return np.empty(0, np.int64), np.empty(0, np.int64)
    h = np.empty(len(tokens), np.uint64)
    last = None
    for i, t in enumerate(tokens):
        if t == last:
            h[i] = SAME
        else:
            v = memo.get(t)
            if v is None:
                if len(memo) > 300_000:
                    memo.clear()
                v = memo[t] = _token_hash(t)
            h[i] = v
            last = t
    pairs = (h[:-1] * np.uint64(0x9E3779B97F4A7C15) + h[1:] + np.uint64(1)) * np.uint64(0xC2B2AE3D27D4EB4F)
    mix = np.concatenate([h * np.uint64(0x9E3779B97F4A7C15), pairs]) >> np.uint64(64 - bits)
    return np.unique(mix.astype(np.int64), return_counts=True)


def values(count: np.ndarray) -> np.ndarray:
    """Square roots of the counts, of norm one."""
    return np.sqrt(count) / np.sqrt(max(1, count.sum()))


@dataclass
class QualityModel:
    bits: int
    bias: float
    buckets: np.ndarray  # sorted, of non-zero weights
    weights: np.ndarray

    def score_texts(self, texts: list[str]) -> np.ndarray:
        dense = np.zeros(1 << self.bits)
        dense[self.buckets] = self.weights
        memo: dict[str, int] = {}
        out = np.empty(len(texts))
        for i, t in enumerate(texts):
            where, count = features(t, self.bits, memo)
            out[i] = self.bias + dense[where] @ values(count)
        return 1 / (1 + np.exp(-np.clip(out, -35, 35)))


def fit_ftrl(rows: list[tuple[np.ndarray, np.ndarray]], labels: np.ndarray, bits: int, alpha: float = 0.5, beta: float = 1.0, l1: float = 0.02, l2: float = 0.1, epochs: int = 6, seed: int = 7, default_score: float = 0.5) -> QualityModel:
    """Per-coordinate follow-the-regularised-leader (proximal) on sparse rows of buckets and counts, in a
    seeded order; values are made from the counts when a row's turn comes, so the rows stay small."""
    none = np.empty(0, np.int64)
    if len(set(labels.tolist())) < 2:
        share = float(labels.mean()) if len(labels) else default_score
        share = min(max(share, 1e-6), 1 - 1e-6)
        return QualityModel(bits, float(np.log(share / (1 - share))), none, np.empty(0))
    z, n = np.zeros((1 << bits) + 1), np.zeros((1 << bits) + 1)
    rng = np.random.default_rng(seed)
    pos = labels.mean()
    weight = np.where(labels == 1, 0.5 / pos, 0.5 / (1 - pos))
    at_bias = 1 << bits

    def solve(zi: np.ndarray, ni: np.ndarray) -> np.ndarray:
        return np.where(np.abs(zi) <= l1, 0.0, -(zi - np.sign(zi) * l1) / ((beta + np.sqrt(ni)) / alpha + l2))

    for _ in range(epochs):
        for i in rng.permutation(len(rows)):
            where = np.append(rows[i][0], at_bias)
            value = np.append(values(rows[i][1]), 1.0)
            w = solve(z[where], n[where])
            p = 1 / (1 + np.exp(-np.clip(w @ value, -35, 35)))
            g = (p - labels[i]) * weight[i] * value
            sigma = (np.sqrt(n[where] + g * g) - np.sqrt(n[where])) / alpha
            z[where] += g - sigma * w
            n[where] += g * g
    w = solve(z, n)
    keep = np.flatnonzero(w[:-1])
    return QualityModel(bits, float(w[-1]), keep, w[keep])


def _feature_columns(texts: list[str], bits: int) -> tuple[list, list]:
    memo: dict[str, int] = {}
    rows = [features(t, bits, memo) for t in texts]
    return [r[0].astype(np.int32) for r in rows], [r[1].astype(np.int32) for r in rows]


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, use: Column | None, max_rows: int, id_col: str = "doc_id") -> DataFrame:
    """At most ``max_rows`` labelled documents: those whose id hashes lowest.

    The bound makes both the broadcast of the drawn ids and what fitting gathers independent of
    the corpus; the draw depends on ids only.
    """
    drawn = labels.select(F.col(id_col).alias("__id"), F.col(label).cast("int").alias("__label")).where(F.col("__label").isin(0, 1) & F.col("__id").isNotNull())
    if use is not None:
        drawn = drawn.withColumnRenamed("__id", id_col).where(use).withColumnRenamed(id_col, "__id")
    drawn = common.draw(drawn, "__id", max_rows)
    return docs.select(F.col(id_col).alias("__id"), F.col("text")).join(F.broadcast(drawn), "__id")


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", use: Column | None = None, bits: int = 18, max_rows: int = 3000, default_score: float = 0.5) -> QualityModel:
    """Fit on a bounded sample of labelled rows (``max_rows``); ``use`` filters rows by their id."""
    sample = labelled_sample(docs, labels, label, use, max_rows)
    kinds = [("where", T.ArrayType(T.IntegerType())), ("count", T.ArrayType(T.IntegerType()))]
    common.tidy(docs.sparkSession)
    got = common.with_text_columns(sample, "text", partial(_feature_columns, bits=bits), kinds, keep=["__id", "__label"]).toArrow().combine_chunks()
    order = pc.sort_indices(got, [("__id", "ascending"), ("__label", "ascending")]).to_pylist()
    parts = []
    for name in ("where", "count"):
        chunks = got[name].chunks
        flat = chunks[0] if chunks else pa.array([], pa.list_(pa.int32()))
        ends, held = flat.offsets.to_pylist(), flat.values.to_numpy()
        parts.append([held[ends[i] : ends[i + 1]] for i in order])
    labels_of = got["__label"].to_numpy().astype(float)[order]
    return fit_ftrl(list(zip(*parts, strict=True)), labels_of, bits, default_score=default_score)


def _scored(texts: list[str], model: QualityModel) -> list[np.ndarray]:
    s = model.score_texts(texts)
    return [s, (s >= 0.5).astype(np.int32)]


def score(docs: DataFrame, model: QualityModel, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Append ``score`` (double in 0..1) and ``predicted`` (int); every row is returned."""
    return common.with_text_columns(docs, text_col, partial(_scored, model=model), [("score", T.DoubleType()), ("predicted", T.IntegerType())], keep)
