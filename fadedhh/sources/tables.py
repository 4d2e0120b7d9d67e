"""Inputs: the given tables, other file formats, file streams, and small in-memory rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from fadedhh.shipping import ensure_shipped


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A parquet table of a folder."""
    ensure_shipped(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load_as(spark: SparkSession, fmt: str, path: str, schema: str, **options) -> DataFrame:
    """csv, json, orc, parquet or text with an explicit schema (nothing is inferred)."""
    return spark.read.format(fmt).options(**options).schema(schema).load(path)


def stream(spark: SparkSession, path: str, schema, files_per_trigger: int = 1, fmt: str = "parquet") -> DataFrame:
    """A folder of files as a stream."""
    return spark.readStream.format(fmt).schema(schema).option("maxFilesPerTrigger", files_per_trigger).load(path)


def rate(spark: SparkSession, rows_per_second: int = 1000) -> DataFrame:
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()


def rows(spark: SparkSession, data: list, schema: str) -> DataFrame:
    return spark.createDataFrame(data, schema)
