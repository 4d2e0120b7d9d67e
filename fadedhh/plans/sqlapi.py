"""SQL surface: functions, a table function and views for users who write SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fadedhh.functions.decay import DecaySpec
from fadedhh.operators import sketch
from fadedhh.operators.params import SketchParams

WEIGHTS = {
    "exp": "exp(param * cast(tick - landmark as double) / unit)",
    "poly": "pow(cast(tick - landmark as double) / unit, param)",
    "dyadic": "pow(2.0D, cast(floor((tick - landmark) / param) as double))",
}


def register(spark: SparkSession) -> None:
    """Temporary SQL functions faded_exp, faded_poly and faded_dyadic (at, landmark, param, unit), in plain expressions
    that the optimiser sees through, and the table function faded_hh."""
    for name, body in WEIGHTS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION faded_{name}(tick BIGINT, landmark BIGINT, param DOUBLE, unit DOUBLE) RETURNS DOUBLE RETURN {body}")
    spark.udtf.register("faded_hh", table_function())


def table_function():
    """faded_hh(TABLE(cells), raw count, phi, norm, seed): the query over a sketch given as a table of fixed size."""
    from pyspark.sql.functions import udtf

    class FadedHeavyHitters:
        def __init__(self):
            self.cells = {}
            self.args = None

        def eval(self, cells, count: float, phi: float, norm: float, d: int, w: int, seed: int):
            self.args = (count, phi, norm, d, w, seed)
            self.cells[cells["row"], cells["col"]] = (cells["i1"], cells["f1"], cells["i2"], cells["f2"])

        def terminate(self):
            import numpy as np

            from fadedhh.functions.hashing import RowHashes

            if not self.args:
                return
            count, phi, norm, d, w, seed = self.args
            found = sorted({c[0] for c in self.cells.values() if c[1] > phi * count})
            at = RowHashes(d, w, seed).arrays(np.array(found, np.int64)) if found else None
            for k, item in enumerate(found):
                est = min(self._value(self.cells.get((r, int(at[r, k]))), item) for r in range(d))
                if est > phi * count:
                    yield item, est / norm

        @staticmethod
        def _value(c, item):
            if c is None:
                return 0.0
            i1, f1, i2, f2 = c
            return f1 if i1 == item else f2

    return udtf(FadedHeavyHitters, returnType="item: long, est: double")


def cell_fold(weighted: DataFrame, *keys: str, k: int = 2) -> DataFrame:
    """(keys, cell): the summary of each group's occurrences in stream order, as an aggregate of built-in functions."""
    from fadedhh.functions import cell

    seq = weighted.where("x > 0").groupBy(*keys).agg(F.sort_array(F.collect_list(F.struct("ord", "item", "x"))).alias("s"))
    return seq.select(*keys, cell.fold(F.transform("s", lambda r: cell.singleton(r["item"], r["x"])), k).alias("cell"))


def views(cells: DataFrame, count: DataFrame, params: SketchParams, phi: float, now: int, prefix: str = "") -> None:
    """Temporary views <prefix>sketch_cells, <prefix>sketch_meta and <prefix>heavy_hitters."""
    cells.createOrReplaceTempView(f"{prefix}sketch_cells")
    meta = count.select(F.col("c").alias("lcount"), *[F.lit(v).alias(k) for k, v in params.describe().items()])
    meta.createOrReplaceTempView(f"{prefix}sketch_meta")
    sketch.heavy_hitters(cells, count, params, phi, now).createOrReplaceTempView(f"{prefix}heavy_hitters")


def weight_sql(spec: DecaySpec) -> str:
    """The registered function's call for a decay, with at and landmark left as names."""
    return f"faded_{spec.kind}(tick, landmark, {spec.param!r}D, {float(spec.unit)!r}D)"
