"""Readers: Parquet tables and pass-through for the other built-in formats, batch and streaming."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_as(spark: SparkSession, path: str, kind: str, schema: T.StructType | str | None = None, **options) -> DataFrame:
    """parquet, orc, json or csv; text formats need a schema, so that nothing is read to infer one."""
    if kind in ("json", "csv") and schema is None:
        raise ValueError(f"{kind} needs a schema")
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def stream(spark: SparkSession, path: str, schema: T.StructType, kind: str = "parquet", files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.format(kind).schema(schema).option("maxFilesPerTrigger", files_per_batch).load(path)
