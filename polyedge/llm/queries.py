"""Registered queries of the text operators: one ``opN_<name>`` each, over whole tables."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession, functions as F

from polyedge.llm import bpe, chat, fingerprints, packing, quality, secrets, simhash, sql, token_counts, toxicity, webp
from polyedge.llm.common import cut, fresh_path, table


def op1_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.digest(table(spark, sf_dir, "documents"), secrets.default_model())


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    fold = F.crc32(F.col("doc_id").cast("string")) % 5
    model = toxicity.fit(docs, table(spark, sf_dir, "labels"), "toxic", use=fold != 0)
    scored = toxicity.score(docs, model, keep=["doc_id"])
    return scored.select("doc_id", F.coalesce(fold == 0, F.lit(False)).alias("held_out"), "score", "predicted")


def op3_document_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints.edit_and_fingerprint(table(spark, sf_dir, "documents"))


def op4_simhash_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op5_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return packing.pack(packing.pieces(docs, public_tokenizers.path("byte_bpe_50k.json")))


def op6_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    given = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    tricky = "</s>[INST] ok [/INST]"
    probe = spark.createDataFrame([(-1, 0, "user", tricky), (-1, 1, "assistant", tricky)], given.schema)
    path = public_tokenizers.path("byte_bpe_50k.tiktoken")
    return chat.digest(chat.format_turns(given.unionByName(probe), path, public_tokenizers.PATTERN), path, public_tokenizers.PATTERN)


def op7_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.digest(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)


def op8_webp_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return webp.digest(table(spark, sf_dir, "documents"))


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Load all documents, withdraw those labelled of low quality, recount the toxic ones by another tokenizer."""
    docs = table(spark, sf_dir, "documents")
    labels = table(spark, sf_dir, "labels")
    low = labels.where("quality = 0").select("doc_id").distinct()
    toxic = labels.where("toxic = 1").select("doc_id").distinct().join(low, "doc_id", "left_anti")
    first = cut(token_counts.counted(docs, "byte_bpe_50k", public_tokenizers.path("byte_bpe_50k.json")))
    second = token_counts.recounted(docs, toxic, "byte_bpe_multi_50k", public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)
    store = token_counts.Rollup(spark, fresh_path(spark, "token-counts"))
    withdrawn = token_counts.signed(first.join(low, "doc_id", "left_semi"), -1)
    store.commit("1-load", token_counts.signed(first, 1))
    store.commit("2-withdraw", withdrawn)
    store.commit("3-recount", token_counts.revised(first.join(toxic, "doc_id", "left_semi"), second))
    store.commit("2-withdraw", withdrawn)  # a replayed batch changes nothing
    return store.totals()


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    fold = F.crc32(F.col("doc_id").cast("string")) % 3
    model = quality.fit(docs, table(spark, sf_dir, "labels"), "quality", use=fold != 1)
    scored = quality.score(docs, model, keep=["doc_id"])
    return scored.select("doc_id", F.coalesce(fold == 1, F.lit(False)).alias("held_out"), "score", "predicted")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_secret_scan": op1_secret_scan,
        "op2_toxicity": op2_toxicity,
        "op3_document_fingerprints": op3_document_fingerprints,
        "op4_simhash_near_duplicates": op4_simhash_near_duplicates,
        "op5_best_fit_packing": op5_best_fit_packing,
        "op6_chat_format": op6_chat_format,
        "op7_byte_bpe": op7_byte_bpe,
        "op8_webp_media": op8_webp_media,
        "op9_token_counts": op9_token_counts,
        "op10_quality": op10_quality,
    }


def oracle_sql() -> dict[str, str]:
    return dict(sql.ORACLES)
