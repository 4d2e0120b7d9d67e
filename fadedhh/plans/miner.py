"""The whole pipeline: local sketches, reduction, query."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fadedhh.operators import sketch
from fadedhh.operators.params import SketchParams
from fadedhh.shipping import fixed_width
from fadedhh.sources.scratch import scratch_path


@dataclass
class Mined:
    """A global sketch with its raw count, ready for queries."""

    cells: DataFrame
    count: DataFrame
    params: SketchParams

    def heavy_hitters(self, phi: float, now: int, strict: bool = True) -> DataFrame:
        return sketch.heavy_hitters(self.cells, self.count, self.params, phi, now, strict)

    def estimate(self, items: DataFrame, now: int) -> DataFrame:
        return sketch.point_estimate(self.cells, self.params, items, now)

    def verified(self, weighted: DataFrame, phi: float, now: int, strict: bool = True) -> DataFrame:
        """(item, f): the answer with exact frequencies from a second scan; no item below the threshold is left."""
        return sketch.verify(self.heavy_hitters(phi, now, strict), weighted, self.params, phi, now, self.count)

    def exact_heavy_hitters(self, weighted: DataFrame, phi: float, now: int) -> DataFrame:
        """(item, est): the whole answer with exact frequencies from a second scan; no item above the threshold is missed."""
        return sketch.exact_heavy_hitters(self.cells, self.count, weighted, self.params, phi, now)

    def top_k(self, k: int, now: int) -> DataFrame:
        return sketch.top_k(self.cells, self.params, k, now)

    def exact_top_k(self, weighted: DataFrame, k: int, now: int) -> DataFrame:
        """(item, est): the k heaviest of all items of the stream, with exact frequencies from further scans."""
        return sketch.exact_top_k(self.cells, weighted, self.params, k, now)


def mine_weighted(weighted: DataFrame, params: SketchParams, shard: str | None = None, combine: bool = True) -> Mined:
    """Sketches a weighted stream by the kernel, at once: the job ends in a stored grid of fixed size, which queries read as often as
    they like. Without a shard column each input partition is a shard."""
    spark = weighted.sparkSession
    path = scratch_path(spark, "grid")
    with fixed_width(spark):
        sketch.reduced(sketch.local_sketches(weighted, params, combine, shard), params).coalesce(1).write.parquet(path)
    return Mined(*sketch.split_count(spark.read.schema(sketch.CELLS).parquet(path)), params)


def mine(stream: DataFrame, params: SketchParams, phi: float, now: int, measure: str | None = None, strict: bool = True) -> DataFrame:
    """Heavy hitters of a stream (item, at) at time ``now``."""
    params.check_support(phi, strict)
    return mine_weighted(sketch.weigh(stream, params, now, measure), params).heavy_hitters(phi, now, strict)


def mine_folded(weighted: DataFrame, params: SketchParams, shards: int, fan_in: int = 64) -> Mined:
    """The reference form: ordered folds in the JVM; ``weighted`` has shard and ord."""
    local = sketch.local_cells_folded(weighted, params)
    return Mined(sketch.unpack(sketch.merge_folded(local, shards, fan_in)), sketch.global_count(weighted), params)


def mine_grouped(weighted: DataFrame, params: SketchParams, group: str, values: list) -> tuple[DataFrame, DataFrame]:
    """(cells, counts) with a column ``g``, the place of the group in ``values``: one scan and one reduction for a sketch per
    listed value of a low-cardinality column. A task holds a grid per value."""
    number = F.array_position(F.array(*[F.lit(v) for v in values]), F.col(group)).cast("int")
    local = sketch.local_sketches(weighted.where(F.col(group).isin(values)).withColumn("shard", number), params)
    return sketch.reduce_groups(local, params)


def heavy_hitters_grouped(cells: DataFrame, counts: DataFrame, params: SketchParams, group: str, phi: float, values: list, now: int) -> DataFrame:
    """(group, item, est): every group's own query, all at once. Both sides that are broadcast are of fixed size."""
    hot = cells.join(F.broadcast(counts), "g").where(F.col("f1") > F.lit(phi) * F.col("c")).select("g", F.col("i1").alias("item")).distinct()
    kept = sketch.raw_estimates(cells, params, hot, "g").join(F.broadcast(counts), "g").where(F.col("est") > F.lit(phi) * F.col("c"))
    name = F.element_at(F.array(*[F.lit(v) for v in values]), F.col("g"))
    return kept.select(name.alias(group), "item", (F.col("est") / F.lit(params.decay.g(now - params.landmark))).alias("est"))


def verified_grouped(weighted: DataFrame, params: SketchParams, group: str, phi: float, values: list) -> DataFrame:
    """(group, item, f): the grouped answer with exact raw frequencies, from a second scan of its items only."""
    cells, counts = mine_grouped(weighted, params, group, values)
    answer = heavy_hitters_grouped(cells, counts, params, group, phi, values, params.landmark)
    name = F.element_at(F.array(*[F.lit(v) for v in values]), F.col("g"))
    sums = weighted.join(F.broadcast(answer.select(group, "item")), [group, "item"], "left_semi").groupBy(group, "item").agg(F.sum("x").alias("f"))
    return sums.join(F.broadcast(counts.select(name.alias(group), "c")), group).where(F.col("f") > F.lit(phi) * F.col("c")).select(group, "item", "f")
