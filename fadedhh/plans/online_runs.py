"""The events table replayed as a stream, and its results once the replay has ended."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fadedhh.functions.times import between_days, micros
from fadedhh.operators import sketch
from fadedhh.operators.params import SketchParams
from fadedhh.plans import workloads as wl
from fadedhh.sources.scratch import scratch_path
from fadedhh.sources.tables import load, stream
from fadedhh.streaming import online


def _replay(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The table's files as a stream; a glob lets the path be one file or a folder."""
    schema = load(spark, sf_dir, "events").schema
    return stream(spark, f"{sf_dir}/events.parque[t]", schema)


def _finish(frame: DataFrame, path: str, mode: str) -> DataFrame:
    """Runs a stream to its end into parquet and reads that."""
    spark = frame.sparkSession
    q = frame.writeStream.format("parquet").outputMode(mode).option("checkpointLocation", f"{path}/check").trigger(availableNow=True).start(f"{path}/out")
    q.awaitTermination()
    return spark.read.parquet(f"{path}/out")


def final_answer(spark: SparkSession, sf_dir: str, params: SketchParams, sites: int, phi: float) -> DataFrame:
    """Sites hold blocks of the stream; after the replay the coordinator queries their newest snapshots. Cells equal those
    of the batch fold over the same shards: sites replay in order and the merge goes by site."""
    n = load(spark, sf_dir, "events").agg(F.max("event_id") + 1).first()[0] or 1
    rows = _replay(spark, sf_dir).where(between_days("ts", "2024-01-01", "2024-01-31"))
    rows = wl.adapt(rows, F.col("user_id"), micros("ts"), F.col("event_id"))
    weighted = sketch.weigh(rows, params, wl.EVENTS_TO).withColumn("site", F.expr(f"cast(ord * {sites} div {n} as int)")).select("site", "item", "x", "ord")
    path = scratch_path(spark, "sites")
    q = online.run_sites(weighted, params).writeStream.foreachBatch(online.snapshot_writer(params, path)).option("checkpointLocation", f"{path}/check").trigger(availableNow=True).start()
    q.awaitTermination()
    from fadedhh.functions import cell
    from fadedhh.sources import sketch_io

    local, count = sketch_io.read(spark, path, params)
    merged = sketch.unpack(sketch.merge_folded(local.select("shard", "row", "col", cell.from_fields().alias("cell")), sites))
    return sketch.heavy_hitters(merged, count, params, phi, wl.EVENTS_TO)


def window_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily counts per event type from the stream."""
    return _complete(online.windows(_replay(spark, sf_dir), "ts", "1 day", None, "event_type"), spark)


def session_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions of users, closed by six idle hours."""
    return _complete(online.sessions(_replay(spark, sf_dir), "ts", "6 hours", "user_id"), spark)


def _complete(frame: DataFrame, spark: SparkSession) -> DataFrame:
    path = scratch_path(spark, "stream")

    def keep(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/out")

    q = frame.writeStream.outputMode("complete").foreachBatch(keep).option("checkpointLocation", f"{path}/check").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(frame.schema).parquet(f"{path}/out")
