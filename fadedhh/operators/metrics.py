"""Accuracy measures of an answer against exact frequencies (both raw or both normalised)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def truth(exact: DataFrame, phi: float) -> DataFrame:
    total = exact.agg(F.sum("f").alias("c"))
    return exact.crossJoin(F.broadcast(total)).where(F.col("f") > F.lit(phi) * F.col("c")).select("item", "f")


def misses(answer: DataFrame, true: DataFrame) -> DataFrame:
    """True heavy hitters not reported."""
    return true.join(answer, "item", "left_anti")


def false_positives(answer: DataFrame, true: DataFrame) -> DataFrame:
    return answer.join(true, "item", "left_anti")


def relative_errors(answer: DataFrame, exact: DataFrame) -> DataFrame:
    """(item, f, est, abs_err, rel_err) of the reported items."""
    gap = F.abs(F.col("est") - F.col("f"))
    return answer.join(exact, "item").select("item", "f", "est", gap.alias("abs_err"), (gap / F.col("f")).alias("rel_err"))


def summary(answer: DataFrame, exact: DataFrame, phi: float) -> DataFrame:
    """One row: truth, reported, hits, precision (1 when nothing is reported), recall (1 when nothing is true), average
    relative error of reported true heavy hitters, maximum and mean absolute error of the reported items."""
    total = exact.agg(F.sum("f").alias("c"))
    both = exact.join(answer, "item", "left").crossJoin(F.broadcast(total))
    heavy, told = F.col("f") > F.lit(phi) * F.col("c"), F.col("est").isNotNull()
    gap = F.abs(F.col("est") - F.col("f"))
    one = both.agg(
        F.count_if(heavy).alias("truth"), F.count_if(told).alias("reported"), F.count_if(heavy & told).alias("hits"),
        F.coalesce(F.avg(F.when(heavy & told, gap / F.col("f"))), F.lit(0.0)).alias("are"),
        F.coalesce(F.max(F.when(told, gap)), F.lit(0.0)).alias("abs_err_max"), F.coalesce(F.avg(F.when(told, gap)), F.lit(0.0)).alias("abs_err_mean"),
    )
    ratio = lambda n, d: F.when(F.col(d) == 0, F.lit(1.0)).otherwise(F.col(n) / F.col(d))
    return one.select("truth", "reported", "hits", ratio("hits", "reported").alias("precision"), ratio("hits", "truth").alias("recall"), "are", "abs_err_max", "abs_err_mean")


def bound_violations(estimates: DataFrame, exact: DataFrame, eps: float) -> DataFrame:
    """(items, violations, rate): items whose error reaches eps times the total; the rate is expected below delta."""
    total = exact.agg(F.sum("f").alias("c"))
    both = exact.join(estimates, "item").crossJoin(F.broadcast(total))
    bad = F.count_if(F.col("est") - F.col("f") >= F.lit(eps) * F.col("c"))
    return both.agg(F.count("*").alias("items"), bad.alias("violations"), (bad / F.count("*")).alias("rate"))


def missed_candidates(cells: DataFrame, true: DataFrame) -> DataFrame:
    """(truth, missed): heavy hitters that are majority candidate in none of their cells."""
    found = cells.select(F.col("i1").alias("item")).distinct()
    return true.join(found.withColumn("r", F.lit(1)), "item", "left").agg(F.count("*").alias("truth"), F.count_if(F.col("r").isNull()).alias("missed"))


def set_ops(answer: DataFrame, true: DataFrame) -> DataFrame:
    """(part, item): the answer split against the truth by set operations."""
    a, b = answer.select("item"), true.select("item")
    tag = lambda part, df: df.select(F.lit(part).alias("part"), "item")
    return tag("both", a.intersect(b)).union(tag("only_answer", a.exceptAll(b))).union(tag("only_truth", b.exceptAll(a)))
