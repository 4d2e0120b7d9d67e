"""Count-Min counters over decayed weights: linear, so plain aggregation builds and merges them."""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fadedhh.shipping import arrow_map

from .params import SketchParams
from .sketch import row_hashes


def build(weighted: DataFrame, params: SketchParams) -> DataFrame:
    """(row, col, f)."""
    return row_hashes(weighted, params).groupBy("row", "col").agg(F.sum("x").alias("f"))


def merge(*parts: DataFrame) -> DataFrame:
    """Counters of the union of streams: cell-wise sums."""
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.groupBy("row", "col").agg(F.sum("f").alias("f"))


def estimate(counters: DataFrame, params: SketchParams, items: DataFrame) -> DataFrame:
    """(item, est): the smallest counter over the rows. The counters (d x w rows at most) are broadcast."""
    probe = items.select("item", F.posexplode(F.array(*params.hashes.columns(F.col("item")))).alias("row", "col"))
    return probe.join(F.broadcast(counters), ["row", "col"], "left").groupBy("item").agg(F.min(F.coalesce("f", F.lit(0.0))).alias("est"))


def heavy_hitters(weighted: DataFrame, params: SketchParams, phi: float) -> DataFrame:
    """(item, est): heap candidates re-estimated by the merged counters. Every partition keeps, beside its own
    counters, the items whose running estimate exceeds phi times its running mass; an item heavy overall
    is heavy in some partition."""
    rows = weighted.select("item", "x")

    def run(batches):
        grid, mass = np.zeros((params.d, params.w)), 0.0
        heap: list = []
        best: dict = {}
        for b in batches:
            item, back = np.unique(b.column(0).to_numpy(), return_inverse=True)
            weight = np.bincount(back, b.column(1).to_numpy())
            at = params.hashes.arrays(item)
            for r in range(params.d):
                grid[r] += np.bincount(at[r], weight, params.w)
            mass += weight.sum()
            est = grid[np.arange(params.d)[:, None], at].min(axis=0)
            for i, e in zip(item[est > phi * mass].tolist(), est[est > phi * mass].tolist()):
                best[i] = e
                heapq.heappush(heap, (e, i))
            while heap and heap[0][0] <= phi * mass:
                e, i = heapq.heappop(heap)
                if best.get(i) == e:
                    del best[i]
        yield pa.RecordBatch.from_arrays([pa.array(list(best), pa.int64())], names=["item"])

    items = arrow_map(rows, run, "item long").distinct()
    total = weighted.agg(F.coalesce(F.sum("x"), F.lit(0.0)).alias("c"))
    est = estimate(build(weighted, params), params, items)
    return est.crossJoin(F.broadcast(total)).where(F.col("est") > F.lit(phi) * F.col("c")).select("item", "est")
