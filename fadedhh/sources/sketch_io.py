"""Sketches at rest: cells and metadata as versioned parquet."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fadedhh.operators.params import SketchParams


def write(cells: DataFrame, count: DataFrame, params: SketchParams, path: str, snapshot: int, site: int = 0) -> None:
    """Adds a snapshot: ``cells/`` and ``meta/``, partitioned by snapshot. Metadata goes last, so a snapshot that
    can be seen is whole."""
    cells.withColumn("site", F.lit(site)).withColumn("snapshot", F.lit(snapshot)).write.mode("append").partitionBy("snapshot").parquet(f"{path}/cells")
    meta = count.select(F.lit(site).alias("site"), F.col("c").alias("lcount"), F.lit(json.dumps(params.describe())).alias("params"), F.lit(snapshot).alias("snapshot"))
    meta.write.mode("append").partitionBy("snapshot").parquet(f"{path}/meta")


def newest(meta: DataFrame, as_of: int | None = None, *more: str) -> DataFrame:
    """(site, snapshot, lcount): per site the newest snapshot at or before ``as_of``, with ``more`` columns."""
    rows = meta if as_of is None else meta.where(F.col("snapshot") <= as_of)
    return rows.groupBy("site").agg(F.max("snapshot").alias("snapshot"), *[F.max_by(c, "snapshot").alias(c) for c in ("lcount", *more)])


def newest_at(meta: DataFrame, times: DataFrame) -> DataFrame:
    """(as_of, site, snapshot, lcount): for every time in ``times`` (as_of) the newest snapshot of each site at or before it. The
    times are gone through once, in order with the snapshots: no pairing of all with all."""
    from pyspark.sql import Window as W

    sites = meta.select("site").distinct()
    asked = times.select("as_of").distinct().crossJoin(F.broadcast(sites)).select("site", F.col("as_of").alias("at"), F.lit(1).alias("asked"), F.lit(None).alias("snapshot"), F.lit(None).alias("lcount"))
    rows = asked.unionByName(meta.select("site", F.col("snapshot").alias("at"), F.lit(0).alias("asked"), "snapshot", "lcount"))
    before = W.partitionBy("site").orderBy("at", "asked").rowsBetween(W.unboundedPreceding, 0)
    last = F.last(F.when(F.col("asked") == 0, F.struct("snapshot", "lcount")), ignorenulls=True).over(before)
    return rows.withColumn("last", last).where("asked = 1 and last is not null").select(F.col("at").alias("as_of"), "site", "last.snapshot", "last.lcount")


def read(spark: SparkSession, path: str, params: SketchParams, as_of: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(site cells as shards, count) of the newest snapshots; refuses sketches built with other parameters."""
    meta = spark.read.parquet(f"{path}/meta")
    check_params([r["params"] for r in meta.select("params").distinct().collect()], params)
    pick = newest(meta, as_of)
    cells = spark.read.parquet(f"{path}/cells").join(F.broadcast(pick.select("site", "snapshot")), ["site", "snapshot"])
    local = cells.select(F.col("site").alias("shard"), "row", "col", "i1", "f1", "i2", "f2")
    return local, pick.agg(F.coalesce(F.sum("lcount"), F.lit(0.0)).alias("c"))


def read_rebased(spark: SparkSession, path: str, params: SketchParams, as_of: int | None = None) -> tuple[DataFrame, DataFrame, SketchParams]:
    """(site cells as shards, count, parameters) of the newest snapshots of sites that may have moved their landmarks: all are
    scaled to the latest one, which the parameters name."""
    meta = spark.read.parquet(f"{path}/meta")
    check_params([r["params"] for r in meta.select("params").distinct().collect()], params)
    pick = newest(meta, as_of, "landmark")
    last = pick.agg(F.max("landmark")).first()[0]
    moved = params if last is None else params.with_(landmark=int(last))
    back = F.exp(F.lit(params.decay.param / params.decay.unit) * (F.col("landmark") - F.lit(moved.landmark))) if params.decay.kind == "exp" else F.lit(1.0)
    pick = pick.withColumn("factor", back)
    cells = spark.read.parquet(f"{path}/cells").drop("landmark").join(F.broadcast(pick.select("site", "snapshot", "factor")), ["site", "snapshot"])
    local = cells.select(F.col("site").alias("shard"), "row", "col", "i1", (F.col("f1") * F.col("factor")).alias("f1"), "i2", (F.col("f2") * F.col("factor")).alias("f2"))
    return local, pick.agg(F.coalesce(F.sum(F.col("lcount") * F.col("factor")), F.lit(0.0)).alias("c")), moved


def check_params(found: list[str], params: SketchParams) -> None:
    for text in found:
        if json.loads(text) != json.loads(json.dumps(params.describe())):
            raise ValueError(f"sketch was built with {text}, not {json.dumps(params.describe())}")
