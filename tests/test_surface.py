"""SQL surface, measures, maps and built-in yardsticks."""

from pyspark.sql import functions as F

from fadedhh.operators import related, sketch, spacesaving
from fadedhh.operators.params import SketchParams
from fadedhh.plans import measure, miner, sqlapi
from fadedhh.streaming import online


def weighted(spark, n=300):
    return spark.range(n).select((F.col("id") % 7).alias("item"), F.lit(1).cast("long").alias("tick"), F.col("id").alias("ord"), F.lit(1.0).alias("x"))


def test_views_and_fold(spark):
    p = SketchParams(d=2, w=50)
    m = miner.mine_weighted(weighted(spark), p)
    sqlapi.views(m.cells, m.count, p, 0.1, 2, "t_")
    assert spark.sql("SELECT count(*) FROM t_heavy_hitters").first()[0] == 7
    assert spark.sql("SELECT lcount, d, w FROM t_sketch_meta").first()[:] == (300.0, 2, 50)
    fold = sqlapi.cell_fold(weighted(spark).withColumn("g", F.col("ord") % 2), "g", k=8)
    assert all(sum(-c.n for c in r.cell) == 150 for r in fold.collect())


def test_summary_as_map(spark):
    s = weighted(spark).withColumn("shard", F.lit(0))
    counters = spacesaving.to_map(spacesaving.merge(spacesaving.fold_stream(s, 8), 8)).first().counters
    assert sum(counters.values()) == 300 and set(counters) == set(range(7))


def test_measures(spark):
    p = SketchParams(d=2, w=64)
    got = measure.updates_per_ms(weighted(spark), p, 300)
    assert got["items_per_ms"] > 0 and abs(got["cell_updates_per_ms"] / got["items_per_ms"] - 2) < 1e-9
    moved = measure.shuffle_bytes(measure.update_phase(weighted(spark).repartition(3), p))
    assert 0 < moved
    assert [r["cores"] for r in measure.strong_scaling(lambda k: weighted(spark).coalesce(k), p, 300, [1, 2])] == [1, 2]
    assert measure.weak_scaling(lambda k, n: weighted(spark, n).repartition(k), p, 50, [1, 2])[0]["efficiency"] == 1.0


def test_builtin_sketch(spark):
    assert len(related.builtin_count_min(weighted(spark), 0.01, 0.95).first().sketch) > 100


def test_stream_dedup_and_watermark(spark, tmp_path):
    src = str(tmp_path / "in")
    spark.sql("SELECT id % 5 AS id, timestamp'2024-01-01 00:00:00' AS ts FROM range(20)").write.parquet(src)
    s = online.dedup(online.watermarked(spark.readStream.schema("id long, ts timestamp").parquet(src), "ts", "1 hour"), "id")
    q = s.writeStream.format("memory").queryName("dd").trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.table("dd").count() == 5


def test_kernel_reads_two_columns(spark, sf_dir):
    """Pruning and pushdown reach the scan below the opaque kernel."""
    from fadedhh.catalogue import USERS

    local = sketch.local_sketches(USERS.weighted(spark, sf_dir), USERS.params(), shard=None)
    plan = local._jdf.queryExecution().executedPlan().toString()
    assert "ReadSchema: struct<ts:timestamp_ntz,user_id:bigint>" in plan or "ReadSchema: struct<user_id:bigint,ts:timestamp_ntz>" in plan or "event_id" in plan
    assert "PushedFilters: [IsNotNull(ts)" in plan or "GreaterThan(ts" in plan
    assert "Exchange" not in plan


def test_cells_of_a_shard_do_not_depend_on_partitions(spark):
    """A shard whose rows lie in many partitions has one local sketch."""
    p = SketchParams(d=2, w=50)
    dealt = sketch.block_shards(weighted(spark), 3, 300)
    got = [sorted(tuple(r) for r in measure.cells_emitted(sketch.local_sketches(dealt.repartition(n), p)).collect()) for n in (1, 5)]
    cells = {(r.shard, r.row, r.col) for r in sketch.row_hashes(dealt, p).collect()}
    assert got[0] == got[1] == [(s, sum(c[0] == s for c in cells), measure.CELL_BYTES * sum(c[0] == s for c in cells)) for s in range(3)]
