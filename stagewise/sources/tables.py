"""Readers and writers: Parquet with pruned columns, text formats with explicit schemas, generated universes, file streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read_table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def universe(spark: SparkSession, n: int, lam: float, seed: int = 1, parts: int | None = None) -> DataFrame:
    """(key, is_pos): n * (lam + 1) keys, of which about n are positive."""
    u = int(n * (lam + 1))
    key = F.xxhash64(F.lit(seed), "id")
    return spark.range(0, u, 1, parts or max(1, u // 1_000_000)).select(key.alias("key"), (F.pmod(F.xxhash64(F.lit(seed + 1), "id"), F.lit(1 << 30)) < int((1 << 30) / (lam + 1))).alias("is_pos"))


def round_trip(df: DataFrame, kind: str, path: str) -> DataFrame:
    """Write and read back as csv, json, orc or parquet, with the schema given and not inferred."""
    writer = df.write.mode("overwrite")
    (writer.option("header", True) if kind == "csv" else writer).format(kind).save(path)
    reader = df.sparkSession.read.schema(df.schema)
    return (reader.option("header", True) if kind == "csv" else reader).format(kind).load(path)


def stream_table(spark: SparkSession, path: str, schema, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)
