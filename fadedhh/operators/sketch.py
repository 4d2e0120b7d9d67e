"""The faded sketch on Spark: local sketches, their reduction, and the two-stage query.

Streams are DataFrames with item (long), tick (long) and ord (a total order); ``weigh`` adds x, the raw
forward weight. Cells are rows (row, col, i1, f1, i2, f2); an absent row is an empty cell.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fadedhh.functions import cell
from fadedhh.functions.decay import forward_raw
from fadedhh.shipping import arrow_map

from .kernel import NumpySketch, reduce_by_key
from .params import SketchParams

#: Rows that the kernel takes in at once.
PORTION = 1 << 19
CELLS = "row int, col int, i1 long, f1 double, i2 long, f2 double"


def admissible(stream: DataFrame, landmark: int, now: int) -> DataFrame:
    """Rows with an item whose time is after the landmark and not after the query."""
    return stream.where((F.col("tick") > landmark) & (F.col("tick") <= now) & F.col("item").isNotNull())


def weigh(stream: DataFrame, params: SketchParams, now: int, measure: str | None = None) -> DataFrame:
    """Adds x. ``measure`` is a non-negative column that multiplies the weight; negative or null measures go."""
    params.decay.check_span(now - params.landmark)
    rows = admissible(stream, params.landmark, now)
    x = forward_raw(F.col("tick"), params.landmark, params.decay)
    if measure:
        rows = rows.where(F.col(measure) >= 0)
        x = x * F.col(measure)
    return rows.withColumn("x", x)


def block_shards(stream: DataFrame, p: int, n: int, ord_col: str = "ord") -> DataFrame:
    """Contiguous blocks of a dense order 0..n-1 by arithmetic: no shuffle."""
    return stream.withColumn("shard", F.expr(f"cast({ord_col} * {p} div {max(n, 1)} as int)"))


def block_shards_by_range(stream: DataFrame, p: int, ord_col: str = "ord") -> DataFrame:
    """Contiguous blocks of any order, by sampled ranges."""
    return stream.repartitionByRange(p, ord_col).withColumn("shard", F.spark_partition_id())


def row_hashes(weighted: DataFrame, params: SketchParams) -> DataFrame:
    """One row per item occurrence and sketch row: adds row and col."""
    at = F.posexplode(F.array(*params.hashes.columns(F.col("item")))).alias("row", "col")
    return weighted.select("*", at)


def local_cells_folded(weighted: DataFrame, params: SketchParams) -> DataFrame:
    """Local sketches by an ordered fold per (shard, row, col), all in the JVM: (shard, row, col, cell).

    It gathers the occurrences of a cell of a shard, so it is for small streams and as the reference.
    """
    one = row_hashes(weighted.where("x > 0"), params).groupBy("shard", "row", "col")
    seq = one.agg(F.sort_array(F.collect_list(F.struct("ord", "item", "x"))).alias("seq"))
    singles = F.transform("seq", lambda r: cell.singleton(r["item"], r["x"]))
    return seq.select("shard", "row", "col", cell.fold(singles).alias("cell"))


def local_sketches(weighted: DataFrame, params: SketchParams, combine: bool = True, shard: str | None = "shard") -> DataFrame:
    """Local sketches by the numpy kernel: (shard, row, col, i1, f1, i2, f2), a row -1 holding the shard's count.

    Without a shard column every partition is a shard: nothing is shuffled, and a task holds one sketch. With
    one, rows stay where they are and a task holds one sketch per shard it meets.
    """
    jvm = params.profile == "xx64"
    cols = params.hashes.columns(F.col("item")) if jvm else []
    lead = [F.col(shard).cast("int").alias("shard")] if shard else []
    rows = weighted.select("item", "x", *[c.alias(f"h{j}") for j, c in enumerate(cols)], *lead)

    def portions(batches):
        """Arrow batches joined up to a bounded number of rows, so that more equal items meet."""
        part, size = [], 0
        for b in batches:
            part.append(b)
            size += b.num_rows
            if size >= PORTION:
                yield pa.Table.from_batches(part)
                part, size = [], 0
        if part:
            yield pa.Table.from_batches(part)

    def run(batches):
        held: dict[int, NumpySketch] = {}
        own = TaskContext.get().partitionId()
        for t in portions(batches):
            item, x = t.column(0).to_numpy(), t.column(1).to_numpy()
            hashed = np.stack([t.column(2 + j).to_numpy() for j in range(params.d)]).astype(np.int64) if jvm else None
            s = t.column("shard").to_numpy() if shard else None
            for k in [own] if s is None else np.unique(s).tolist():
                on = slice(None) if s is None or (s[0] == k and (s == k).all()) else s == k
                held.setdefault(k, NumpySketch(params)).update(item[on], x[on], combine, hashed[:, on] if jvm else None)
        for k, sketch in held.items():
            yield sketch.rows(k)

    return arrow_map(rows, run, "shard int, " + CELLS)


def counts_of(local: DataFrame) -> DataFrame:
    """(shard, lcount) from kernel output."""
    return local.where("row = -1").groupBy("shard").agg(F.sum("f1").alias("lcount"))


def global_count(weighted: DataFrame) -> DataFrame:
    """One row, c: the raw decayed count."""
    return weighted.agg(F.coalesce(F.sum("x"), F.lit(0.0)).alias("c"))


def count_from_local(local: DataFrame) -> DataFrame:
    return local.where("row = -1").agg(F.coalesce(F.sum("f1"), F.lit(0.0)).alias("c"))


def merge_folded(local: DataFrame, shards: int, fan_in: int = 64) -> DataFrame:
    """Reduction of (shard, row, col, cell) in shard order, ``fan_in`` shards at a time, level by level, in
    the JVM. Equal input gives equal output: the tree is fixed. Returns (row, col, cell)."""
    level, left = local, shards
    while True:
        left = -(-left // fan_in)
        grouped = level.select(F.floor(F.col("shard") / fan_in).cast("int").alias("shard"), F.col("shard").alias("from"), "row", "col", "cell")
        level = grouped.groupBy("shard", "row", "col").agg(F.sort_array(F.collect_list(F.struct("from", "cell"))).alias("parts"))
        level = level.select("shard", "row", "col", cell.fold(F.transform("parts", lambda x: x["cell"])).alias("cell"))
        if left <= 1:
            return level.select("row", "col", "cell")


def reduced(local: DataFrame, params: SketchParams, partitions: int | None = None) -> DataFrame:
    """The merged grid of kernel output, with rows -1 whose f1 add up to the count, by one shuffle: each task streams the partial
    cells of its share of the grid through the vectorised merge, holding at most the grid and one batch; counts add up on
    the way. Partial cells of a cell are merged in the order in which they arrive: runs may differ in the counters they
    end up with, within the same bounds. The folded form has a fixed order."""
    w = params.w
    parts = partitions or int(local.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def run(batches):
        grid = NumpySketch(params)
        for b in batches:
            row, col = (b.column(k).to_numpy().astype(np.int64) for k in (0, 1))
            cells = tuple(b.column(k).fill_null(0).to_numpy(zero_copy_only=False) for k in range(2, 6))
            grid.count += float(cells[1][row < 0].sum())
            on = row >= 0
            key, cells = reduce_by_key(row[on] * w + col[on], tuple(x[on] for x in cells))
            grid.absorb(key, cells)
        yield grid.rows(0).select(["row", "col", "i1", "f1", "i2", "f2"])

    rows = local.select("row", "col", "i1", "f1", "i2", "f2").repartition(min(parts, 64), "row", "col")
    return arrow_map(rows, run, CELLS)


def split_count(merged: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(cells, count) of a merged grid."""
    return merged.where("row >= 0"), merged.where("row = -1").agg(F.coalesce(F.sum("f1"), F.lit(0.0)).alias("c"))


def reduce_local(local: DataFrame, params: SketchParams, partitions: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(cells, count) of kernel output; both share one shuffle."""
    return split_count(reduced(local, params, partitions))


def reduce_groups(local: DataFrame, params: SketchParams) -> tuple[DataFrame, DataFrame]:
    """(cells, counts) with the shard as a group ``g`` that stays apart: the same reduction, its key led by the group."""
    w = params.w

    def run(batches):
        held: dict[int, NumpySketch] = {}
        for b in batches:
            g, row, col = (b.column(k).to_numpy().astype(np.int64) for k in range(3))
            cells = tuple(b.column(k).fill_null(0).to_numpy(zero_copy_only=False) for k in range(3, 7))
            for k in np.unique(g).tolist():
                grid = held.setdefault(k, NumpySketch(params))
                grid.count += float(cells[1][(row < 0) & (g == k)].sum())
                on = (row >= 0) & (g == k)
                grid.absorb(*reduce_by_key(row[on] * w + col[on], tuple(x[on] for x in cells)))
        for k, grid in held.items():
            yield grid.rows(k)

    rows = local.select("shard", "row", "col", "i1", "f1", "i2", "f2").repartition("shard", "row", "col")
    merged = arrow_map(rows, run, "g int, " + CELLS)
    return merged.where("row >= 0"), merged.where("row = -1").groupBy("g").agg(F.sum("f1").alias("c"))


def merge_sketches(local: DataFrame, params: SketchParams, partitions: int | None = None) -> DataFrame:
    """The merged cells alone."""
    return reduce_local(local, params, partitions)[0]


def unpack(cells: DataFrame) -> DataFrame:
    """(row, col, cell) to field columns."""
    return cells.select(*[c for c in cells.columns if c != "cell"], *cell.fields(F.col("cell")))


def merge_two(a: DataFrame, b: DataFrame) -> DataFrame:
    """Merge of two sketches in field form, by a full outer join of their cells."""
    left = a.select("row", "col", cell.from_fields().alias("ca"))
    right = b.select("row", "col", cell.from_fields().alias("cb"))
    none = F.expr(cell.EMPTY)
    both = left.join(right, ["row", "col"], "full_outer")
    return unpack(both.select("row", "col", cell.merge(F.coalesce("ca", none), F.coalesce("cb", none)).alias("cell")))


def rebase(cells: DataFrame, params: SketchParams, landmark: int) -> tuple[DataFrame, SketchParams]:
    """The sketch under another landmark; only for decays whose weights do not depend on it."""
    if not params.decay.landmark_free:
        raise ValueError("only exponential or absent decay can move the landmark")
    factor = F.lit(params.decay.g(params.landmark - landmark))
    moved = cells.withColumn("f1", F.col("f1") * factor).withColumn("f2", F.col("f2") * factor)
    return moved, params.with_(landmark=landmark)


def candidates(cells: DataFrame, count: DataFrame, phi: float) -> DataFrame:
    """Distinct majority candidates whose counter alone passes the threshold: fewer than d / phi items."""
    return cells.crossJoin(F.broadcast(count)).where(F.col("f1") > F.lit(phi) * F.col("c")).select(F.col("i1").alias("item")).distinct()


def raw_estimates(cells: DataFrame, params: SketchParams, items: DataFrame, *by: str) -> DataFrame:
    """(item, est): smallest over the rows of what the item's cell allows: its counter, or the smaller one. ``by`` names
    columns of both sides that keep several grids apart. A grid is of fixed size (d x w rows), so it is the side that is broadcast."""
    probe = items.select(*by, "item", F.posexplode(F.array(*params.hashes.columns(F.col("item")))).alias("row", "col"))
    hit = probe.join(F.broadcast(cells), [*by, "row", "col"], "left")
    return hit.groupBy(*by, "item").agg(F.min(_allowed()).alias("est"))


def _allowed() -> Column:
    """What a joined cell allows its item: its counter, or the smaller one."""
    return F.when(F.col("i1") == F.col("item"), F.col("f1")).when(F.col("i2") == F.col("item"), F.col("f2")).otherwise(F.coalesce("f2", F.lit(0.0)))


def possible(weighted: DataFrame, cells: DataFrame, params: SketchParams, least: DataFrame) -> DataFrame:
    """(item, x): occurrences of the items whose raw frequency may reach the one number in ``least``, a column of that name. Cells never
    underestimate, so no item that reaches it is left out (a billionth of it is left for sums in another order). Rows stay where
    they are: each meets the rows of the grid, which are broadcast."""
    rows = weighted.select("item", "x").crossJoin(F.broadcast(least.select((F.col("least") * (1 - 1e-9)).alias("least"))))
    for j, at in enumerate(params.hashes.columns(F.col("item"))):
        grid = cells.where(F.col("row") == j).select(F.col("col").alias("at"), "i1", "f1", "i2", "f2")
        rows = rows.join(F.broadcast(grid), at == F.col("at"), "left").where(_allowed() >= F.col("least")).select("item", "x", "least")
    return rows.select("item", "x")


def point_estimate(cells: DataFrame, params: SketchParams, items: DataFrame, now: int) -> DataFrame:
    """Estimated decayed frequencies at time ``now`` of given items."""
    return raw_estimates(cells, params, items).withColumn("est", F.col("est") / F.lit(params.decay.g(now - params.landmark)))


def heavy_hitters(cells: DataFrame, count: DataFrame, params: SketchParams, phi: float, now: int, strict: bool = True) -> DataFrame:
    """(item, est): items whose estimate exceeds phi times the decayed count. Thresholds are raw, since the
    normaliser divides both sides; it is applied once, to the answer."""
    params.check_support(phi, strict)
    found = raw_estimates(cells, params, candidates(cells, count, phi))
    kept = found.crossJoin(F.broadcast(count)).where(F.col("est") > F.lit(phi) * F.col("c"))
    return kept.select("item", (F.col("est") / F.lit(params.decay.g(now - params.landmark))).alias("est"))


def verify(answer: DataFrame, weighted: DataFrame, params: SketchParams, phi: float, now: int, count: DataFrame | None = None) -> DataFrame:
    """(item, f): exact decayed frequencies of the answer's items by a second scan, those above the threshold. ``count`` is
    the sketch's raw count; without it a further scan finds it. The answer has fewer than d / phi rows, so it may
    be broadcast."""
    exact = weighted.join(F.broadcast(answer.select("item")), "item", "left_semi").groupBy("item").agg(F.sum("x").alias("f"))
    kept = exact.crossJoin(F.broadcast(global_count(weighted) if count is None else count)).where(F.col("f") > F.lit(phi) * F.col("c"))
    return kept.select("item", (F.col("f") / F.lit(params.decay.g(now - params.landmark))).alias("f"))


def exact_heavy_hitters(cells: DataFrame, count: DataFrame, weighted: DataFrame, params: SketchParams, phi: float, now: int) -> DataFrame:
    """(item, est): all items above phi times the decayed count and no others, for any phi and grid: a second scan sums up the
    items that the sketch allows to pass, whether or not one of its cells has them as candidate."""
    least = count.select((F.lit(phi) * F.col("c")).alias("least"))
    sums = possible(weighted, cells, params, least).groupBy("item").agg(F.sum("x").alias("f"))
    kept = sums.crossJoin(F.broadcast(count)).where(F.col("f") > F.lit(phi) * F.col("c"))
    return kept.select("item", (F.col("f") / F.lit(params.decay.g(now - params.landmark))).alias("est"))


def top_k(cells: DataFrame, params: SketchParams, k: int, now: int) -> DataFrame:
    """The k heaviest of all majority candidates, by estimate then item."""
    every = cells.select(F.col("i1").alias("item")).distinct()
    return point_estimate(cells, params, every, now).orderBy(F.desc("est"), "item").limit(k)


def exact_top_k(cells: DataFrame, weighted: DataFrame, params: SketchParams, k: int, now: int) -> DataFrame:
    """(item, est): the k heaviest of all items by exact frequency then item, by two more scans. The exact frequencies of the k items
    that the sketch puts first give a least value; all items that the sketch allows to reach it are summed up."""
    first = weighted.join(F.broadcast(top_k(cells, params, k, now).select("item")), "item", "left_semi").groupBy("item").agg(F.sum("x").alias("f"))
    least = first.agg(F.when(F.count("*") >= k, F.min("f")).otherwise(F.lit(0.0)).alias("least"))
    top = possible(weighted, cells, params, least).groupBy("item").agg(F.sum("x").alias("f")).orderBy(F.desc("f"), "item").limit(k)
    return top.select("item", (F.col("f") / F.lit(params.decay.g(now - params.landmark))).alias("est"))


def label(answer: DataFrame, dimension: DataFrame, key: str, columns: list[str]) -> DataFrame:
    """Attaches names from a dimension table to an answer; the answer is the small side."""
    dim = dimension.select(F.col(key).alias("item"), *columns)
    return dim.join(F.broadcast(answer), "item")
