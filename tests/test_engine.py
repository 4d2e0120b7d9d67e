"""Edge cases of streams, sketches at rest, rebasing, profiles and sharding."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from fadedhh.functions.decay import DecaySpec
from fadedhh.functions.hashing import P61, RowHashes
from fadedhh.operators import countmin, exact, invariants, sketch
from fadedhh.operators.params import SketchParams
from fadedhh.plans import miner
from fadedhh.sources import sketch_io, sinks, tables

SCHEMA = "item long, tick long, ord long"


def stream(spark, rows):
    return spark.createDataFrame(rows, SCHEMA)


def test_admissible_rows(spark):
    s = stream(spark, [(1, 0, 0), (1, 1, 1), (None, 2, 2), (2, None, 3), (3, 11, 4), (4, 10, 5)])
    p = SketchParams(d=2, w=8, landmark=0, decay=DecaySpec.dyadic(1))
    got = sketch.weigh(s, p, 10).orderBy("ord").collect()
    assert [(r.item, r.x) for r in got] == [(1, 2.0), (4, 1024.0)]


def test_empty_and_single(spark):
    p = SketchParams(d=1, w=1)
    s = stream(spark, [])
    assert miner.mine(s, p, 0.5, 10, strict=False).count() == 0
    s = stream(spark, [(7, 1, 0)] * 3)
    assert [tuple(r) for r in miner.mine(s, p, 0.5, 10, strict=False).collect()] == [(7, 3.0)]


def test_zero_weights_are_ignored(spark):
    s = stream(spark, [(1, 1, 0), (2, 2, 1)]).withColumn("x0", F.lit(0.0))
    p = SketchParams(d=2, w=4)
    assert sketch.local_sketches(sketch.weigh(s, p, 9, "x0"), p, shard=None).where("row >= 0").count() == 0


def test_same_answer_under_any_sharding_and_order(spark):
    rng = np.random.default_rng(3)
    rows = [(int(i), int(t), k) for k, (i, t) in enumerate(zip(rng.zipf(1.4, 3000) % 200, rng.integers(1, 20, 3000)))]
    p = SketchParams(d=4, w=600, decay=DecaySpec.dyadic(1))
    answers = set()
    for parts in (1, 3, 8):
        w = sketch.weigh(stream(spark, rows).repartition(parts), p, 20)
        m = miner.mine_weighted(w, p)
        answers.add(tuple(sorted(r.item for r in m.heavy_hitters(0.05, 20).collect())))
        assert invariants.norm_equivalence(m.cells, countmin.build(w, p)).first().max_gap == 0
    truth = {r.item for r in exact.heavy_hitters(sketch.weigh(stream(spark, rows), p, 20), 0.05).collect()}
    assert answers == {tuple(sorted(truth))}


def test_answer_set_does_not_depend_on_query_time(spark):
    rows = [(i % 5 if i % 3 else 9, 1 + i % 7, i) for i in range(300)]
    p = SketchParams(d=3, w=300, decay=DecaySpec.exp(0.1, 1))
    m = miner.mine_weighted(sketch.weigh(stream(spark, rows), p, 7), p)
    a = {r.item: r.est for r in m.heavy_hitters(0.1, 7).collect()}
    b = {r.item: r.est for r in m.heavy_hitters(0.1, 17).collect()}
    assert set(a) == set(b) and all(abs(a[i] / b[i] - np.e) < 1e-9 for i in a)


def test_rebase_matches_other_landmark(spark):
    rows = [(i % 7, 5 + i % 11, i) for i in range(200)]
    p = SketchParams(d=2, w=50, landmark=0, decay=DecaySpec.exp(0.3, 1))
    q = p.with_(landmark=4)
    moved, r = sketch.rebase(miner.mine_weighted(sketch.weigh(stream(spark, rows), p, 16), p).cells, p, 4)
    direct = miner.mine_weighted(sketch.weigh(stream(spark, rows), q, 16), q).cells
    assert r == q
    a = {(x.row, x.col): x.f1 + x.f2 for x in moved.collect()}
    b = {(x.row, x.col): x.f1 + x.f2 for x in direct.collect()}
    assert a.keys() == b.keys() and all(abs(a[k] / b[k] - 1) < 1e-9 for k in a)
    with pytest.raises(ValueError):
        sketch.rebase(moved, p.with_(decay=DecaySpec.poly(2)), 1)


def test_overflow_is_refused(spark):
    p = SketchParams(decay=DecaySpec.exp(1.0, 1))
    with pytest.raises(OverflowError):
        sketch.weigh(stream(spark, [(1, 1, 1)]), p, 5000)


@pytest.mark.parametrize("profile", ["mod31", "mod61", "xx64"])
def test_profiles_keep_mass(spark, profile):
    rows = [(i * 2**33 + 5, 1, i) for i in range(500)]
    p = SketchParams(d=3, w=40, profile=profile)
    cells = miner.mine_weighted(sketch.weigh(stream(spark, rows), p, 2), p).cells
    assert {r.mass for r in invariants.row_mass(cells).collect()} == {500.0}


def test_mod61_against_integers():
    h = RowHashes(3, 97, 5, "mod61")
    x = np.array([0, 1, 2**60, P61 - 1, 123456789012345678], np.int64)
    want = [[(a * int(v) + b) % P61 % 97 for v in x] for a, b in h.coefficients(P61)]
    assert h.arrays(x).tolist() == want


def test_tree_of_folds(spark):
    rows = [(i % 13, 1 + i % 5, i) for i in range(400)]
    p = SketchParams(d=2, w=5, decay=DecaySpec.dyadic(1))
    w = sketch.block_shards(sketch.weigh(stream(spark, rows), p, 6), 20, 400)
    for fan_in in (2, 5, 64):
        cells = miner.mine_folded(w, p, 20, fan_in).cells
        assert invariants.norm_equivalence(cells, countmin.build(w, p)).first().max_gap == 0


def test_snapshots_and_parameter_check(spark, tmp_path):
    p = SketchParams(d=2, w=9)
    path = str(tmp_path / "sk")
    for snap, n in ((1, 10), (2, 25)):
        m = miner.mine_weighted(sketch.weigh(stream(spark, [(3, 1, i) for i in range(n)]), p, 2), p)
        sketch_io.write(m.cells, m.count, p, path, snap)
    local, count = sketch_io.read(spark, path, p)
    assert count.first().c == 25 and sketch.merge_sketches(local, p).agg(F.max("f1")).first()[0] == 25
    assert sketch_io.read(spark, path, p, as_of=1)[1].first().c == 10
    with pytest.raises(ValueError):
        sketch_io.read(spark, path, p.with_(w=10))


def test_sources_and_sinks(spark, tmp_path):
    df = tables.rows(spark, [(1, 2.0)], "item long, est double")
    for fmt in ("parquet", "json", "csv", "orc"):
        path = str(tmp_path / fmt)
        sinks.write(df, path, fmt)
        assert [tuple(r) for r in tables.load_as(spark, fmt, path, "item long, est double").collect()] == [(1, 2.0)]
    assert tables.rate(spark).isStreaming


def test_late_rows_change_nothing(spark, tmp_path):
    """A shuffled replay through the stateful sites: same count, same mass, same answer."""
    from fadedhh.streaming import online

    rows = [(i % 4 if i % 2 else 1, 1 + i // 40, i) for i in range(200)]
    p = SketchParams(d=2, w=30, decay=DecaySpec.dyadic(1))
    w = sketch.weigh(stream(spark, rows), p, 9).withColumn("site", (F.col("ord") % 2).cast("int")).select("site", "item", "x", "ord")
    src = str(tmp_path / "in")
    w.orderBy(F.rand(3)).repartition(3).write.parquet(src)
    q = online.run_sites(tables.stream(spark, src, w.schema), p).writeStream.foreachBatch(online.snapshot_writer(p, str(tmp_path / "out"))).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    got = {r.item: r.est for r in online.query_now(spark, str(tmp_path / "out"), p, 0.3, 9).collect()}
    want = {r.item: r.f for r in exact.heavy_hitters(w, 0.3, p.decay.g(9)).collect()}
    assert got == want


def test_replayed_batch_changes_nothing(spark, tmp_path):
    """A micro-batch that is run again after a failure replaces its snapshot."""
    from fadedhh.streaming import online

    p = SketchParams(d=2, w=30, decay=DecaySpec.none())
    rows = [(0, 1, 0, 0, 0, 5, 3.0, None, 0.0), (0, 1, 0, -1, 0, 0, 3.0, None, 0.0)]
    batch = spark.createDataFrame(rows, "site int, seen long, landmark long, row int, col int, i1 long, f1 double, i2 long, f2 double")
    write = online.snapshot_writer(p, str(tmp_path))
    for batch_id in (0, 0, 1, 1):
        write(batch, batch_id)
    local, count, _ = sketch_io.read_rebased(spark, str(tmp_path), p)
    assert [r.f1 for r in local.collect()] == [3.0] and count.first().c == 3.0


def test_sites_outlive_the_range_of_doubles(spark, tmp_path):
    """Under exponential decay the landmark moves: a stream of 3,000 half-lives answers like weights taken back from now."""
    import math

    from fadedhh.streaming import online

    p = SketchParams(d=2, w=40, decay=DecaySpec.exp(math.log(2), 1))
    with pytest.raises(OverflowError):
        p.decay.check_span(3000)
    rows = [(i % 2, (i // 10) % 7 if i % 3 else 1, 1 + i, i) for i in range(3000)]
    df = spark.createDataFrame(rows, "site int, item long, tick long, ord long")
    src = str(tmp_path / "in")
    for k in range(3):
        df.where((F.col("ord") >= 1000 * k) & (F.col("ord") < 1000 * (k + 1))).coalesce(1).write.mode("append").parquet(src)
    frames = spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(src)
    q = online.run_sites(frames, p).writeStream.foreachBatch(online.snapshot_writer(p, str(tmp_path / "out"))).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    got = {r.item: r.est for r in online.query_now(spark, str(tmp_path / "out"), p, 0.1, 3000).collect()}
    want: dict = {}
    for _, item, tick, _ in rows:
        want[item] = want.get(item, 0.0) + 2.0 ** (tick - 3000)
    total = sum(want.values())
    assert set(got) == {i for i, f in want.items() if f > 0.1 * total} and all(abs(got[i] - want[i]) < 1e-6 for i in got)


def test_grouped_sketches_stay_apart(spark):
    rows = [(i % 5, 1 + i % 3, i, "ab"[i % 2]) for i in range(300)] + [(9, 1, 300 + i, "a") for i in range(200)]
    df = spark.createDataFrame(rows, "item long, tick long, ord long, g0 string")
    p = SketchParams(d=2, w=50, decay=DecaySpec.dyadic(1))
    w = sketch.weigh(df, p, 3)
    cells, counts = miner.mine_grouped(w, p, "g0", ["a", "b", "none"])
    assert {r.g: r.c for r in counts.collect()} == {k: w.where(f"g0 = '{v}'").agg(F.sum("x")).first()[0] for k, v in ((1, "a"), (2, "b"))}
    got = sorted(map(tuple, miner.verified_grouped(w, p, "g0", 0.15, ["a", "b", "none"]).collect()))
    want = sorted((r.g0, r.item, r.f) for r in exact.grouped_heavy_hitters(w, "g0", 0.15).collect())
    assert got == want and ("a", 9) in {x[:2] for x in got}


def test_fixed_width_settings_are_put_back(spark):
    from fadedhh.shipping import fixed_width

    keys = ("spark.sql.execution.arrow.maxBytesPerBatch", "spark.sql.execution.arrow.maxRecordsPerBatch")
    before = [spark.conf.get(k, None) for k in keys]
    with pytest.raises(ZeroDivisionError), fixed_width(spark):
        assert spark.conf.get(keys[0]) == str(2**31 - 1)
        1 / 0
    assert [spark.conf.get(k, None) for k in keys] == before


def test_newest_snapshots_in_one_pass(spark):
    meta = spark.createDataFrame([(s, 3 * k + s, float(k)) for k in range(20) for s in range(3) if (k + s) % 4], "site int, snapshot long, lcount double")
    got = sorted(map(tuple, sketch_io.newest_at(meta, spark.createDataFrame([(1,), (7,), (7,), (500,)], "as_of long")).collect()))
    want = sorted((t, *r) for t in (1, 7, 500) for r in map(tuple, sketch_io.newest(meta, t).select("site", "snapshot", "lcount").collect()))
    assert got == want


def test_cost_counters():
    from fadedhh.plans import measure

    p = SketchParams(d=4, w=100)
    assert measure.worker_bytes(p) == 12_800 and measure.sketch_traffic(p, 3) == 48_000
    assert [measure.reduction_depth(n, f) for n, f in ((1, 2), (2, 2), (512, 2), (512, 64), (65, 64))] == [1, 1, 9, 2, 2]


def test_exact_top_k_on_small_grids(spark):
    """More items than a grid has cells: the k heaviest come out exactly, ties by item, whatever the sketch puts first."""
    s = spark.range(4000).select((F.col("id") * 7919 % 1009).alias("item"), (1 + F.col("id") % 5).alias("tick"), F.col("id").alias("ord"))
    for w, k in ((4, 10), (64, 10), (64, 2000)):
        p = SketchParams(d=2, w=w, decay=DecaySpec.dyadic(1))
        weighted = sketch.weigh(s, p, 9)
        got = [tuple(r) for r in miner.mine_weighted(weighted, p).exact_top_k(weighted, k, 9).collect()]
        want = exact.decayed_frequency(weighted).orderBy(F.desc("f"), "item").limit(k).collect()
        assert got == [(r.item, r.f / p.decay.g(9)) for r in want]


def test_exact_heavy_hitters_outside_the_guarantee(spark):
    """Grids whose own answer has intruders and misses items: after the second scan it is the exact one."""
    s = spark.range(4000).select(F.floor(F.sqrt(F.col("id") * 7919 % 4001)).alias("item"), (1 + F.col("id") % 5).alias("tick"), F.col("id").alias("ord"))
    for w, phi in ((1, 0.02), (4, 0.02), (32, 0.025)):
        p = SketchParams(d=2, w=w, decay=DecaySpec.dyadic(1))
        weighted = sketch.weigh(s, p, 9)
        mined = miner.mine_weighted(weighted, p)
        want = {(r.item, r.f) for r in exact.heavy_hitters(weighted, phi, p.decay.g(9)).collect()}
        assert want and {tuple(r) for r in mined.exact_heavy_hitters(weighted, phi, 9).collect()} == want
        assert {r.item for r in mined.heavy_hitters(phi, 9, strict=False).collect()} != {i for i, _ in want}
