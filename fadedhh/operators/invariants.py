"""What every sketch must satisfy, as queries that count violations."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fadedhh.functions import cell

from .params import SketchParams
from .sketch import raw_estimates, row_hashes


def norm_equivalence(cells: DataFrame, counters: DataFrame) -> DataFrame:
    """(cells, max_gap): both counters of a cell sum to the Count-Min counter of that cell."""
    both = cells.select("row", "col", (F.col("f1") + F.col("f2")).alias("m")).join(counters, ["row", "col"], "full_outer")
    gap = F.abs(F.coalesce("m", F.lit(0.0)) - F.coalesce("f", F.lit(0.0)))
    return both.agg(F.count("*").alias("cells"), F.max(gap).alias("max_gap"))


def row_mass(cells: DataFrame) -> DataFrame:
    """(row, mass): every row of the grid holds the raw decayed count."""
    return cells.groupBy("row").agg(F.sum(F.col("f1") + F.col("f2")).alias("mass"))


def cell_bounds(cells: DataFrame, weighted: DataFrame, params: SketchParams) -> DataFrame:
    """(pairs, under, over, unmonitored, half): item-cell pairs checked, monitored items below their exact
    frequency, estimates above frequency plus the smaller counter, unmonitored items above the smaller counter, and
    cells whose smaller counter exceeds half their mass. All but the first must be 0."""
    per_cell = row_hashes(weighted, params).groupBy("row", "col", "item").agg(F.sum("x").alias("f"))
    both = per_cell.join(F.broadcast(cells), ["row", "col"])
    counter = F.when(F.col("item") == F.col("i1"), F.col("f1")).when(F.col("item") == F.col("i2"), F.col("f2"))
    least = F.col("f2")
    return both.agg(
        F.count("*").alias("pairs"), F.count_if(counter < F.col("f")).alias("under"), F.count_if(counter - least > F.col("f")).alias("over"),
        F.count_if(counter.isNull() & (F.col("f") > least)).alias("unmonitored"), F.count_if(F.col("f2") * 2 > F.col("f1") + F.col("f2")).alias("half"),
    )


def never_under(cells: DataFrame, weighted: DataFrame, params: SketchParams) -> DataFrame:
    """(items, under): items whose point estimate is below their exact frequency."""
    exact = weighted.groupBy("item").agg(F.sum("x").alias("f"))
    est = raw_estimates(cells, params, exact.select("item"))
    return exact.join(est, "item").agg(F.count("*").alias("items"), F.count_if(F.col("est") < F.col("f")).alias("under"))


def tolerance_contract(answer: DataFrame, weighted: DataFrame, phi: float, eps: float) -> DataFrame:
    """(truth, missed, intruders): heavy items not reported, and reported items at or below phi - eps."""
    exact = weighted.groupBy("item").agg(F.sum("x").alias("f"))
    total = exact.agg(F.sum("f").alias("c"))
    both = exact.join(answer.select("item", F.lit(1).alias("r")), "item", "left").crossJoin(F.broadcast(total))
    heavy, light = F.col("f") > F.lit(phi) * F.col("c"), F.col("f") <= F.lit(phi - eps) * F.col("c")
    return both.agg(F.count_if(heavy).alias("truth"), F.count_if(heavy & F.col("r").isNull()).alias("missed"), F.count_if(light & F.col("r").isNotNull()).alias("intruders"))


def summary_deficit(pairs: DataFrame, k: int) -> DataFrame:
    """(mass, deficit) of merging two k-counter summaries, columns a and b: what the kept counters lack of the mass of
    both. With two counters it is 0."""
    size = lambda c: F.aggregate(c, F.lit(0.0), lambda acc, u: acc - u["n"])
    merged = pairs.withColumn("m", cell.merge(F.col("a"), F.col("b"), k))
    return merged.select((size("a") + size("b")).alias("mass"), (size("a") + size("b") - size("m")).alias("deficit"))
