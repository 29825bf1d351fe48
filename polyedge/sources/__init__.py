"""Sources and sinks: declared-schema scans, other formats, streams and idempotent writers."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession, functions as F


def table(spark: SparkSession, sf_dir: str, name: str, columns: Sequence[str] | None = None, where: Column | str | None = None) -> DataFrame:
    """Parquet scan; the filter and the column list reach the reader."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if where is not None:
        df = df.where(where)
    return df.select(*columns) if columns else df


def read(spark: SparkSession, fmt: str, path: str, schema: str | None = None, **options) -> DataFrame:
    """Any reader format of the session: parquet, orc, csv, json, text, jdbc, avro where the jar exists."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def stream(spark: SparkSession, path: str, schema, ts: str = "ts", fmt: str = "parquet", max_files: int = 1) -> DataFrame:
    """File stream whose time column is a UTC timestamp, which a watermark needs."""
    df = spark.readStream.format(fmt).schema(schema).option("maxFilesPerTrigger", max_files).load(path)
    return df.withColumn(ts, F.col(ts).cast("timestamp"))


def write(df: DataFrame, path: str, fmt: str = "parquet", partition_by: Sequence[str] = (), mode: str = "errorifexists") -> None:
    w = df.write.format(fmt).mode(mode)
    (w.partitionBy(*partition_by) if partition_by else w).save(path)


def idempotent(path: str, fmt: str = "parquet"):
    """A ``foreachBatch`` sink: a batch has a folder of its own, so a replay overwrites itself."""

    def sink(df: DataFrame, batch_id: int) -> None:
        df.write.format(fmt).mode("overwrite").save(f"{path.rstrip('/')}/batch={batch_id}")

    return sink
