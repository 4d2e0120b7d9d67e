"""Stream summaries of k counters: sequential build, parallel merge, and what k means for the mass kept."""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fadedhh.functions import cell
from fadedhh.shipping import arrow_map


def fold_stream(weighted: DataFrame, k: int) -> DataFrame:
    """(shard, cell): the summary of each shard in stream order, folded in the JVM (reference form)."""
    seq = weighted.where("x > 0").groupBy("shard").agg(F.sort_array(F.collect_list(F.struct("ord", "item", "x"))).alias("s"))
    return seq.select("shard", cell.fold(F.transform("s", lambda r: cell.singleton(r["item"], r["x"])), k).alias("cell"))


def build(weighted: DataFrame, k: int) -> DataFrame:
    """(shard, mass, cell): a summary per partition by a kernel that adds up equal items of a batch and evicts the
    smallest counter for each newcomer, heaviest newcomers last. The smallest comes from a heap, made anew for each batch, so a
    newcomer costs log k."""
    rows = weighted.select("item", "x")

    def run(batches):
        count: dict[int, float] = {}
        mass = 0.0
        for b in batches:
            item, back = np.unique(b.column(0).to_numpy(), return_inverse=True)
            weight = np.bincount(back, b.column(1).to_numpy())
            mass += float(weight.sum())
            order = np.argsort(weight, kind="stable")
            fresh = []
            for i, x in zip(item[order].tolist(), weight[order].tolist()):
                if i in count:
                    count[i] += x
                elif x > 0:
                    fresh.append((i, x))
            heap = [(f, -i) for i, f in count.items()]
            heapq.heapify(heap)
            for i, x in fresh:
                if len(count) >= k:
                    f, low = heapq.heappop(heap)
                    x += count.pop(-low)
                count[i] = x
                heapq.heappush(heap, (x, -i))
        pairs = sorted(((-f, i) for i, f in count.items()))
        kind = pa.list_(pa.struct([("n", pa.float64()), ("i", pa.int64())]))
        yield pa.RecordBatch.from_arrays([pa.array([mass]), pa.array([[{"n": n, "i": i} for n, i in pairs]], kind)], names=["mass", "cell"])

    made = arrow_map(rows, run, f"mass double, cell {cell.TYPE}")
    return made.select(F.spark_partition_id().alias("shard"), "mass", "cell")


def merge(parts: DataFrame, k: int) -> DataFrame:
    """One row, cell: the shards' summaries merged in shard order. Each holds at most k counters."""
    all_ = parts.agg(F.sort_array(F.collect_list(F.struct("shard", "cell"))).alias("p"))
    return all_.select(cell.fold(F.transform("p", lambda x: x["cell"]), k).alias("cell"))


def to_rows(merged: DataFrame) -> DataFrame:
    return merged.select(F.explode("cell").alias("c")).select(F.col("c.i").alias("item"), (-F.col("c.n")).alias("est"))


def to_map(merged: DataFrame) -> DataFrame:
    """The summary as a map of item to estimate."""
    return merged.select(F.map_from_entries(F.transform("cell", lambda c: F.struct(c["i"], -c["n"]))).alias("counters"))


def norm_deficit(merged: DataFrame, mass: DataFrame) -> DataFrame:
    """(mass, norm, deficit): how much of the stream's mass the counters no longer sum to; 0 for two counters."""
    norm = F.aggregate("cell", F.lit(0.0), lambda a, c: a - c["n"])
    return merged.crossJoin(F.broadcast(mass)).select("mass", norm.alias("norm"), (F.col("mass") - norm).alias("deficit"))


def heavy_hitters(merged: DataFrame, phi: float, mass: DataFrame) -> DataFrame:
    return to_rows(merged).crossJoin(F.broadcast(mass)).where(F.col("est") > F.lit(phi) * F.col("mass")).select("item", "est")
