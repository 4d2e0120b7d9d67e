"""Outputs: answers to files, and streaming sinks."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql.streaming import DataStreamWriter


def write(answer: DataFrame, path: str, fmt: str = "parquet", mode: str = "overwrite", **options) -> None:
    """parquet, orc, json or csv; an answer is small, so one file."""
    answer.coalesce(1).write.format(fmt).options(**options).mode(mode).save(path)


def foreach_batch(stream: DataFrame, fn: Callable[[DataFrame, int], None], checkpoint: str) -> DataStreamWriter:
    return stream.writeStream.foreachBatch(fn).option("checkpointLocation", checkpoint)


def memory(stream: DataFrame, name: str, mode: str = "append") -> DataStreamWriter:
    return stream.writeStream.format("memory").queryName(name).outputMode(mode)
