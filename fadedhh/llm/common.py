"""Helpers shared by the training-data operators: table access, settled tables, graph components."""

from __future__ import annotations

import gc
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fadedhh.shipping import ensure_shipped
from fadedhh.sources.scratch import shared_root


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables, read by Spark so that any store works."""
    ensure_shipped(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def fresh(df: DataFrame, prefix: str) -> str:
    """The prefix, lengthened until no column of ``df`` starts with it: names for passing columns."""
    while any(c.lower().startswith(prefix) for c in df.columns):
        prefix = f"_{prefix}"
    return prefix


def _folder(spark: SparkSession) -> str:
    return f"{shared_root(spark)}/settled-{spark.sparkContext.applicationId}"


def forget(spark: SparkSession) -> None:
    """Deletes all tables this application has settled; to be called once its results are written."""
    jvm = spark.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(_folder(spark))
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def release(spark: SparkSession) -> None:
    """Lets the engine delete the shuffle files of finished jobs now, which it does only once their plans are collected as garbage."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def settle(df: DataFrame) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts lineage, survives lost executors and
    leaves later joins free to choose (and split) their own exchanges."""
    spark = df.sparkSession
    path = f"{_folder(spark)}/{uuid.uuid4().hex}"
    df.write.mode("overwrite").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def connected_components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """(node, comp) for every node of an undirected edge list; comp is the smallest node reachable.

    Alternates hanging larger neighbours on the smallest one and smaller neighbours on each other
    until every node hangs on a root. Work per round is linear in the edges; minima are pre-aggregated before
    each shuffle, so a star of any degree stays spread out. Self loops keep isolated nodes.
    """
    e = settle(
        edges.select(F.col(a).alias("u"), F.col(b).alias("v"))
        .where("u is not null and v is not null")
        .select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
        .distinct()
    )
    nodes = e.select(F.col("u").alias("node")).union(e.select("v")).distinct()
    state = e.where("u <> v")
    for _ in range(max_rounds):
        both = state.union(state.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        low = settle(low)
        large = (
            both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
            .union(low.select("u", F.col("m").alias("v")))
            .where("u <> v").distinct()
        )
        large = settle(large)
        low2 = settle(large.groupBy("u").agg(F.min("v").alias("m")))
        small = (
            large.join(low2, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
            .union(low2.select("u", F.col("m").alias("v")))
            .where("u <> v").distinct()
        )
        state = settle(small)
        twice = state.groupBy("u").agg(F.count("*").alias("c")).where("c > 1").select("u")
        middle = state.select(F.col("v").alias("u")).distinct().join(state.select("u"), "u", "left_semi")
        if twice.union(middle).isEmpty():  # every node hangs on one root: nothing can move any more
            break
    else:
        raise RuntimeError("components did not settle; raise max_rounds")
    return settle(
        nodes.join(state.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("comp")), "node", "left")
        .select("node", F.coalesce("comp", "node").alias("comp"))
    )
