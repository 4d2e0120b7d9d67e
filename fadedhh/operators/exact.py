"""Exact baselines: grouped sums of weights."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def decayed_frequency(weighted: DataFrame) -> DataFrame:
    """(item, f): raw decayed frequency of every item."""
    return weighted.groupBy("item").agg(F.sum("x").alias("f"))


def heavy_hitters(weighted: DataFrame, phi: float, norm: float = 1.0) -> DataFrame:
    """(item, f, share) of items above phi times the total: one aggregation, the total from its result."""
    f = decayed_frequency(weighted)
    total = f.agg(F.sum("f").alias("c"))
    kept = f.crossJoin(F.broadcast(total)).where(F.col("f") > F.lit(phi) * F.col("c"))
    return kept.select("item", (F.col("f") / F.lit(norm)).alias("f"), (F.col("f") / F.col("c")).alias("share"))


def grouped_heavy_hitters(weighted: DataFrame, group: str, phi: float) -> DataFrame:
    """(group, item, f, share): items heavy within their group."""
    f = weighted.groupBy(group, "item").agg(F.sum("x").alias("f"))
    total = f.groupBy(F.col(group).alias("g_")).agg(F.sum("f").alias("c"))
    return f.join(total, F.col(group) == F.col("g_")).where(F.col("f") > F.lit(phi) * F.col("c")).select(group, "item", "f", (F.col("f") / F.col("c")).alias("share"))


def mass_cube(weighted: DataFrame, *cols: str) -> DataFrame:
    """Decayed mass over all subsets of the columns."""
    return weighted.cube(*cols).agg(F.sum("x").alias("f"))


def mass_rollup(weighted: DataFrame, *cols: str) -> DataFrame:
    return weighted.rollup(*cols).agg(F.sum("x").alias("f"))


def mass_sets(weighted: DataFrame, sets: list[list[str]]) -> DataFrame:
    """Decayed mass over the given subsets of columns."""
    cols = list(dict.fromkeys(c for s in sets for c in s))
    return weighted.groupingSets([[F.col(c) for c in s] for s in sets], *cols).agg(F.sum("x").alias("f"))


def mass_pivot(weighted: DataFrame, by: str, pivot: str, values: list) -> DataFrame:
    return weighted.groupBy(by).pivot(pivot, values).agg(F.sum("x"))


def ranked(weighted: DataFrame, k: int) -> DataFrame:
    """(item, f, share, rank, running): the k heaviest with their rank and running share. Ranks are taken after
    the limit, so the single-task window sees k rows."""
    f = decayed_frequency(weighted)
    total = f.agg(F.sum("f").alias("c"))
    top = f.orderBy(F.desc("f"), "item").limit(k).crossJoin(F.broadcast(total))
    order = W.partitionBy().orderBy(F.desc("f"), "item")
    return top.select("item", "f", (F.col("f") / F.col("c")).alias("share"), F.row_number().over(order).alias("rank"), (F.sum("f").over(order.rowsBetween(W.unboundedPreceding, 0)) / F.col("c")).alias("running"))
