"""Online mining: sites keep local sketches of their own streams, a coordinator asks for the heavy hitters.

Each micro-batch updates the sketch of every site it has rows of and writes new snapshots; a query is a batch job over
the newest snapshots, so sites never pause. State is one grid per site, whatever the number of items.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fadedhh.operators import sketch
from fadedhh.operators.kernel import NumpySketch
from fadedhh.operators.params import SketchParams
from fadedhh.shipping import ensure_shipped
from fadedhh.sources import sketch_io

STATE = "items binary, weights binary, count double, seen long, landmark long"
OUT = "site int, seen long, landmark long, row int, col int, i1 long, f1 double, i2 long, f2 double"


#: Natural logarithm of a raw weight beyond which a site moves its landmark.
MOST_LOG = 300.0


def watermarked(stream: DataFrame, ts: str, delay: str) -> DataFrame:
    """Bounds how long site state and windows wait; weights never depend on arrival order."""
    return stream.withWatermark(ts, delay)


def dedup(stream: DataFrame, key: str) -> DataFrame:
    """Drops replayed rows within the watermark."""
    return stream.dropDuplicatesWithinWatermark([key])


def windows(stream: DataFrame, ts: str, width: str, slide: str | None = None, *by: str) -> DataFrame:
    """Counts per tumbling or sliding window."""
    w = F.window(ts, width, slide) if slide else F.window(ts, width)
    out = stream.groupBy(w.alias("w"), *by).agg(F.count("*").alias("n"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *by, "n")


def sessions(stream: DataFrame, ts: str, gap: str, by: str) -> DataFrame:
    """Counts per session: rows of a key with less than the gap between neighbours."""
    out = stream.groupBy(F.session_window(ts, gap).alias("w"), by).agg(F.count("*").alias("n"))
    return out.select(by, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def run_sites(stream: DataFrame, params: SketchParams, site: str = "site") -> DataFrame:
    """Stateful operator: rows (site, item, x) with raw weights x, or (site, item, tick) to be weighted here, in; after each batch
    the whole sketch of each touched site out (rows of cells and a row -1 with the count; ``seen`` orders a site's
    snapshots).

    Rows with a tick, under exponential decay, may run on for ever: before raw weights leave the range of doubles a site
    moves its landmark to its newest row and scales what it holds; ``landmark`` tells to which."""
    ensure_shipped(stream.sparkSession)
    rate = params.decay.param / params.decay.unit if params.decay.kind == "exp" else 0.0
    ticks = "x" not in stream.columns
    if ticks and not params.decay.landmark_free:
        raise ValueError("only exponential or absent decay can move the landmark: give raw weights")

    def step(key, frames, state):
        local = NumpySketch(params)
        seen, landmark = 0, params.landmark
        if state.exists:
            items, weights, count, seen, landmark = state.get
            i, f = np.frombuffer(items, np.int64).reshape(2, -1), np.frombuffer(weights, np.float64).reshape(2, -1)
            local.cells = (i[0].copy(), f[0].copy(), i[1].copy(), f[1].copy())
            local.count = count
        for frame in frames:
            frame = frame.sort_values("ord") if "ord" in frame else frame
            if ticks:
                frame = frame[frame["tick"] > params.landmark]
            if ticks and len(frame):
                newest = int(frame["tick"].max())
                if rate * (newest - landmark) > MOST_LOG:
                    local.scale(math.exp(-rate * (newest - landmark)))
                    landmark = newest
                x = np.exp(rate * (frame["tick"].to_numpy(np.int64) - landmark))
            else:
                x = frame["x"].to_numpy(float) if "x" in frame else np.zeros(0)
            local.update(frame["item"].to_numpy(np.int64), x, combine=False)
            seen += len(frame)
        i1, f1, i2, f2 = local.cells
        state.update((np.stack([i1, i2]).tobytes(), np.stack([f1, f2]).tobytes(), local.count, seen, landmark))
        out = pa.Table.from_batches([local.rows(int(key[0]))]).to_pandas(types_mapper=None)
        out = out.rename(columns={"shard": "site"})
        out.insert(1, "seen", seen)
        out.insert(2, "landmark", landmark)
        out["i2"] = out["i2"].astype("Int64")
        yield out

    return stream.groupBy(site).applyInPandasWithState(step, OUT, STATE, "append", "NoTimeout")


def snapshot_writer(params: SketchParams, path: str):
    """foreachBatch function: writes each touched site's newest sketch as a snapshot numbered by the batch.
    A batch that is run again replaces its snapshot."""

    def write(batch: DataFrame, batch_id: int) -> None:
        last = batch.groupBy(F.col("site").alias("s")).agg(F.max("seen").alias("m"))
        rows = batch.join(F.broadcast(last), F.expr("site = s and seen = m")).select("site", "landmark", "row", "col", "i1", "f1", "i2", "f2")
        cells = rows.where("row >= 0")
        cells.write.mode("overwrite").parquet(f"{path}/cells/snapshot={batch_id}")
        import json

        meta = rows.where("row = -1").select("site", "landmark", F.col("f1").alias("lcount"), F.lit(json.dumps(params.describe())).alias("params"))
        meta.write.mode("overwrite").parquet(f"{path}/meta/snapshot={batch_id}")

    return write


def query_now(spark: SparkSession, path: str, params: SketchParams, phi: float, now: int, as_of: int | None = None) -> DataFrame:
    """Heavy hitters over the newest snapshot of every site, under the latest of their landmarks."""
    local, count, params = sketch_io.read_rebased(spark, path, params, as_of)
    return sketch.heavy_hitters(sketch.merge_sketches(local, params), count, params, phi, now)
