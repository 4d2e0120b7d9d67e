"""Related frequent-item summaries, each with its published guarantee. Streams have item and ord.

All build one summary per partition and merge; what leaves a partition is bounded by the summary's size.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fadedhh.functions.hashing import RowHashes
from fadedhh.shipping import arrow_map

from .params import SketchParams
from .sketch import row_hashes


def _per_partition(rows: DataFrame, step, schema: str, finish):
    """One mergeable summary (a dict of counters) per partition, fed with distinct items of each batch."""

    def run(batches):
        state: dict = {}
        seen = 0
        for b in batches:
            item, count = np.unique(b.column(0).to_numpy(), return_counts=True)
            seen += int(count.sum())
            state = step(state, item.tolist(), count.tolist(), seen)
        yield finish(state, seen)

    return arrow_map(rows.select("item").where("item is not null"), run, schema)


def _shrink(state: dict, k: int) -> dict:
    """Subtracts the (k+1)-th largest count from all and keeps the positive ones: at most k counters."""
    if len(state) <= k:
        return state
    cut = sorted(state.values(), reverse=True)[k]
    return {i: c - cut for i, c in state.items() if c > cut}


def frequent(stream: DataFrame, k: int) -> DataFrame:
    """(item, low): decrement counters; true count - n/(k+1) <= low <= true count, and every item above
    n/(k+1) is there."""

    def step(state, items, counts, _):
        for i, c in zip(items, counts):
            state[i] = state.get(i, 0) + c
        return _shrink(state, k)

    def finish(state, _):
        return pa.RecordBatch.from_arrays([pa.array(list(state), pa.int64()), pa.array(list(state.values()), pa.int64())], names=["item", "low"])

    parts = _per_partition(stream, step, "item long, low long", finish).groupBy("item").agg(F.sum("low").alias("low"))
    cut = parts.orderBy(F.desc("low")).limit(k + 1).agg(F.when(F.count("*") > k, F.min("low")).otherwise(F.lit(0)).alias("cut"))
    return parts.crossJoin(F.broadcast(cut)).where("low > cut").select("item", (F.col("low") - F.col("cut")).cast("long").alias("low"))


def lossy_counting(stream: DataFrame, eps: float) -> DataFrame:
    """(item, low, slack): true count in [low, low + slack], slack <= eps n in all; items above eps n are there.
    A partition prunes, after each batch, counters whose count and slack stay within eps times what it has seen."""

    def step(state, items, counts, seen):
        bucket = math.floor(eps * (seen - sum(counts)))
        for i, c in zip(items, counts):
            low, slack = state.get(i, (0, bucket))
            state[i] = (low + c, slack)
        edge = math.floor(eps * seen)
        return {i: (c, s) for i, (c, s) in state.items() if c + s > edge}

    def finish(state, seen):
        return pa.RecordBatch.from_arrays(
            [pa.array([*state, None], pa.int64()), pa.array([*(c for c, _ in state.values()), 0], pa.int64()), pa.array([*(s for _, s in state.values()), math.floor(eps * seen)], pa.int64())],
            names=["item", "low", "slack"],
        )

    parts = _per_partition(stream, step, "item long, low long, slack long", finish)
    missing = parts.where("item is null").agg(F.coalesce(F.sum("slack"), F.lit(0)).alias("all_slack"))
    kept = parts.where("item is not null").groupBy("item").agg(F.sum("low").alias("low"))
    return kept.crossJoin(F.broadcast(missing)).select("item", "low", F.col("all_slack").cast("long").alias("slack"))


def sticky_sampling(stream: DataFrame, phi: float, eps: float, delta: float, n: int, seed: int = 3) -> DataFrame:
    """(item, count): occurrences counted from the first sampled one on, at the rate that finds every item above
    phi n and loses at most eps n of its count with probability 1 - delta. Sampling is by a seeded hash of the order."""
    t = math.log(1 / (phi * delta)) / eps
    rate = min(1.0, 2 * t / max(n, 1))
    coin = F.pmod(F.xxhash64("ord", F.lit(seed)), F.lit(1 << 30)) < F.lit(int(rate * (1 << 30)))
    first = stream.where(coin).groupBy("item").agg(F.min("ord").alias("since"))
    return stream.join(first, "item").where("ord >= since").groupBy("item").agg(F.count("*").alias("count"))


def signs(params: SketchParams) -> RowHashes:
    return RowHashes(params.d, 2, params.seed + 2000)


def _sign(params: SketchParams):
    return F.element_at(F.array(*signs(params).columns(F.col("item"))), F.col("row") + 1) * 2 - 1


def count_sketch(weighted: DataFrame, params: SketchParams) -> DataFrame:
    """(row, col, f): signed sums; the sign of an item in a row is a further hash of two values."""
    return row_hashes(weighted, params).groupBy("row", "col").agg(F.sum(_sign(params) * F.col("x")).alias("f"))


def count_sketch_estimate(counters: DataFrame, params: SketchParams, items: DataFrame) -> DataFrame:
    """(item, est): median over the rows of the signed counters."""
    probe = items.select("item", F.posexplode(F.array(*params.hashes.columns(F.col("item")))).alias("row", "col"))
    return probe.join(F.broadcast(counters), ["row", "col"], "left").groupBy("item").agg(F.percentile(_sign(params) * F.coalesce("f", F.lit(0.0)), F.lit(0.5)).alias("est"))


def group_test(weighted: DataFrame, params: SketchParams, phi: float, bits: int = 48) -> DataFrame:
    """(item, est): per cell one sum per item bit; a cell heavy overall spells its majority item bit by bit. Items
    found are checked by the cell sums of all rows, so a misspelt one goes."""
    rows = row_hashes(weighted, params)
    sums = [F.sum(F.when(F.shiftright("item", b).bitwiseAND(F.lit(1)) == 1, F.col("x")).otherwise(0.0)).alias(f"b{b}") for b in range(bits)]
    cells = rows.groupBy("row", "col").agg(F.sum("x").alias("f"), *sums)
    total = weighted.agg(F.coalesce(F.sum("x"), F.lit(0.0)).alias("c"))
    heavy = cells.crossJoin(F.broadcast(total)).where(F.col("f") > F.lit(phi) * F.col("c"))
    spelt = sum((F.when(F.col(f"b{b}") * 2 > F.col("f"), F.lit(1 << b)).otherwise(F.lit(0)).cast("long") for b in range(bits)), F.lit(0).cast("long"))
    items = heavy.select(spelt.alias("item")).distinct()
    return hcount_estimate(cells.select("row", "col", "f"), params, items).crossJoin(F.broadcast(total)).where(F.col("est") > F.lit(phi) * F.col("c")).select("item", "est")


def hcount(weighted: DataFrame, params: SketchParams) -> DataFrame:
    """Hashed counters: the grid of Count-Min with its own seed."""
    return row_hashes(weighted, params.with_(seed=params.seed + 1000)).groupBy("row", "col").agg(F.sum("x").alias("f"))


def hcount_estimate(counters: DataFrame, params: SketchParams, items: DataFrame) -> DataFrame:
    probe = items.select("item", F.posexplode(F.array(*params.hashes.columns(F.col("item")))).alias("row", "col"))
    return probe.join(F.broadcast(counters), ["row", "col"], "left").groupBy("item").agg(F.min(F.coalesce("f", F.lit(0.0))).alias("est"))


def builtin_top_k(stream: DataFrame, k: int, capacity: int = 10_000) -> DataFrame:
    """(item, n): the engine's own un-decayed approximate top k."""
    top = stream.agg(F.expr(f"approx_top_k(item, {k}, {max(capacity, k)})").alias("t"))
    return top.select(F.explode("t").alias("r")).select(F.col("r.item").alias("item"), F.col("r.count").alias("n"))


def builtin_count_min(stream: DataFrame, eps: float, confidence: float, seed: int = 1) -> DataFrame:
    """One row, sketch: the engine's own un-decayed Count-Min sketch, serialised."""
    return stream.agg(F.count_min_sketch("item", F.lit(eps), F.lit(confidence), F.lit(seed)).alias("sketch"))
