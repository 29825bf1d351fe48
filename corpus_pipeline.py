"""Corpus pipeline: quality, toxicity, near-duplicates, secrets, packing, each over all that its predecessor kept."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession, functions as F

from polyedge.llm import common, packing, quality, secrets, simhash, toxicity


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier rejects go."""
    model = quality.fit(docs, common.table(spark, sf_dir, "labels"), "quality", default_score=1.0)
    return quality.score(docs, model).where("predicted = 1").select(*docs.columns)


def keep_civil(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity classifier marks go."""
    model = toxicity.fit(docs, common.table(spark, sf_dir, "labels"), "toxic", default_score=0.0)
    return toxicity.score(docs, model).where("predicted = 0").select(*docs.columns)


def keep_distinct(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near-duplicates (five-word shingles, similarity 0.8) the document with the smallest id stays."""
    return simhash.keep_similar(docs)


def remove_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets in texts are replaced by marks; lengths follow."""
    done = secrets.redact(docs, secrets.default_model()).withColumns({"text": F.col("redacted_text"), "n_chars": F.char_length("redacted_text").cast(docs.schema["n_chars"].dataType)})
    return done.select(*docs.columns)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents and their places in training sequences."""
    return packing.pack(packing.pieces(docs, public_tokenizers.path("byte_bpe_50k.json")))


STAGES = [
    ("quality", keep_good),
    ("toxicity", keep_civil),
    ("near_duplicates", keep_distinct),
    ("secrets", remove_secrets),
    ("packing", pack_sequences),
]

#: No stage can be written in SQL; tests hold them against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each result is written and read again as the next one's input."""
    docs = common.table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        path = common.fresh_path(spark, f"stage-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return STAGES[-1][1](spark, docs, sf_dir)
