"""Mixing, chat rendering, embeddings, the graph helper and the pipeline."""

import hashlib
import random
from fractions import Fraction

import brute
import numpy as np
import pytest
from pyspark.sql import functions as F

from fadedhh.llm import chatfmt, embdedup, mixing
from fadedhh.llm.common import connected_components


def test_mix_places_every_row(spark, docs, rows, empty):
    out = mixing.mix(docs, {"src0": 3, "src2": 1}, block_docs=2).collect()
    assert sorted(r.doc_id for r in out) == sorted(r[0] for r in rows)
    assert len({r.mix_order for r in out}) == len(out)
    for s in {r.source for r in out}:
        mine = sorted((r.mix_block, r.mix_slot) for r in out if r.source == s)
        order = sorted(((r.mix_order, hashlib.md5(str(r.doc_id).encode()).hexdigest()) for r in out if r.source == s))
        assert [x[1] for x in order] == sorted(x[1] for x in order)
        assert [x[1] for x in mine] == sorted(x[1] for x in mine)
    assert mixing.mix(empty).count() == 0


def test_mix_keeps_shares_until_a_source_ends(spark):
    rows = [(i, "a" if i % 4 else "b") for i in range(4000)]
    out = mixing.mix(spark.createDataFrame(rows, "doc_id long, source string"), {"a": 0.5, "b": 0.5}, block_docs=1).orderBy("mix_order").collect()
    seen = {"a": 0, "b": 0}
    for t, r in enumerate(out[:1900], 1):
        seen[r.source] += 1
        assert abs(seen["a"] - t / 2) < 1.01
    assert len(out) == 4000


def ideal_gap(blocks, weights, slots):
    """Largest distance of any source from its ideal share, after any slot, by stepping the ideal course."""
    owner = {t: k for k, x in slots.items() for t in x}
    assert sorted(owner) == list(range(sum(blocks.values()))) and all(x == sorted(x) for x in slots.values())
    want, got, gap = dict.fromkeys(blocks, Fraction(0)), dict.fromkeys(blocks, 0), 0
    for t in range(len(owner)):
        time = Fraction(1)
        while time:
            left = {k: blocks[k] - want[k] for k in blocks if blocks[k] > want[k]}
            rate = {k: Fraction(weights[k]) / sum(Fraction(weights[x]) for x in left) for k in left}
            step = min([time, *(left[k] / rate[k] for k in left)])
            for k in left:
                want[k] += step * rate[k]
            time -= step
        got[owner[t]] += 1
        gap = max([gap, *(abs(want[k] - got[k]) for k in blocks)])
    return gap


@pytest.mark.parametrize("blocks, weights", [
    ({"a": 400, **{f"b{k:02}": 9 for k in range(40)}}, {"a": 1, **{f"b{k:02}": Fraction(1, 39) for k in range(40)}}),
    ({"a": 90, "b": 300, "c": 7, "d": 1}, {"a": 2, "b": 7, "c": 3, "d": Fraction(1, 1000)}),
    ({"a": 30, "b": 30, "c": 30}, {"a": 1, "b": 1, "c": 1}),
])
def test_schedule_keeps_the_exact_targets(blocks, weights):
    """Within one block of the true targets over the whole table, also after sources have ended."""
    assert ideal_gap(blocks, weights, mixing.schedule(blocks, weights)[0]) < 1


def test_mix_keeps_a_target_that_no_quantum_divides(spark):
    rows = [(i, "a" if i % 2 else f"b{i % 40:02}") for i in range(8000)]
    weights = {"a": 20, **{f"b{k:02}": 1 for k in range(0, 40, 2)}}
    out = mixing.mix(spark.createDataFrame(rows, "doc_id long, source string"), weights, block_docs=1).orderBy("mix_order").collect()
    seen = 0
    for t, r in enumerate(out, 1):
        seen += r.source == "a"
        assert abs(seen - Fraction(t, 2)) < 1


def test_mix_schedules_every_source_by_its_weight(spark):
    """More sources than MAX_SOURCES: all are named, so each must hold its own share."""
    names = [f"s{k:04}" for k in range(600)]
    rows = [(k * 4 + j, s) for k, s in enumerate(names) for j in range(4)]
    weights = {s: 1 + k % 3 for k, s in enumerate(names)}
    out = mixing.mix(spark.createDataFrame(rows, "doc_id long, source string"), weights, block_docs=1).collect()
    assert sorted(r.mix_slot for r in out) == list(range(2400))
    half = 600  # of weight 3, 2, 1 in turn: no source has ended yet
    for k, s in enumerate(names):
        assert abs(sum(r.source == s and r.mix_slot < half for r in out) - Fraction(half * weights[s], sum(weights.values()))) < 1
    assert {r.mix_phase for r in out if r.mix_slot < half} == {0}


def test_mixing_query_against_brute_force(spark):
    """The whole query: every source's blocks of 16 by md5 of the id, every slot by the slot-by-slot schedule."""
    rng = random.Random(9)
    rows = [(i, rng.choice(["a"] * 9 + ["b"] * 4 + ["c", "d", None])) for i in range(3000)] + [(5000, "e")]
    got = mixing.mixing_query(spark.createDataFrame(rows, "doc_id long, source string")).collect()
    by = {}
    for i, s in rows:
        by.setdefault(s, []).append(i)
    key = {s: f"s:{s}" if s else "n:" for s in by}
    slots = brute.schedule({key[s]: -(-len(x) // 16) for s, x in by.items()}, {key[s]: Fraction(float(len(x)) ** 0.5) for s, x in by.items()})
    want = {}
    for s, x in by.items():
        for r, i in enumerate(sorted(x, key=lambda i: hashlib.md5(str(i).encode()).hexdigest())):
            want[i] = (s, r // 16, slots[key[s]][r // 16], slots[key[s]][r // 16] * 16 + r % 16)
    assert {r.doc_id: (r.source, r.mix_block, r.mix_slot, r.mix_order) for r in got} == want


def test_mix_of_weight_zero_comes_last(spark):
    out = mixing.mix(spark.createDataFrame([(i, "ab"[i % 2]) for i in range(20)], "doc_id long, source string"), {"a": 1, "b": 0}, block_docs=1).orderBy("mix_order").collect()
    assert [r.source for r in out] == ["a"] * 10 + ["b"] * 10


def test_mix_ranks_over_many_buckets(spark):
    docs = spark.range(500).select(F.col("id").alias("doc_id"), F.lit("s").alias("source"))
    got = mixing.ranked(docs, 500, "doc_id", mixing.source_key("source"), bucket_rows=4).select("doc_id", "mix_rank").collect()
    want = sorted(range(500), key=lambda i: hashlib.md5(str(i).encode()).hexdigest())
    assert {r.doc_id: r.mix_rank for r in got} == {d: k for k, d in enumerate(want)}


def test_chat(spark):
    turns = [
        (1, 0, "user", "hi"), (2, 0, "user", "hi"), (2, 1, "assistant", "yes"), (3, 0, "user", "hi"), (3, 1, "assistant", "yes"), (3, 2, "user", None),
        (4, 0, "user", "hi"), (4, 1, "assistant", "yes"), (4, 2, "user", None), (5, 0, "system", "hi"), (6, 5, None, ""), (None, 0, "user", "x"), (7, None, "user", "q"), (7, None, "user", "q"),
    ]
    df = spark.createDataFrame(turns, "conv_id long, turn long, role string, text string").withColumn("n", F.lit(1)).repartition(3)
    got = {r.conv_id: (r.n_turns, r.text) for r in chatfmt.chat_format(df).collect()}
    assert set(got) == {3, 5, 6, 7}
    assert got[3] == (3, "<|user|>\nhi<|end|>\n<|assistant|>\nyes<|end|>\n<|user|>\n<|end|>") and got[7][0] == 2
    assert chatfmt.chat_format(df.limit(0)).count() == 0


def test_chat_is_native(spark, sf_dir):
    from fadedhh.llm import linededup

    docs, conv = spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/conversations.parquet")
    for df in (chatfmt.chat_query(conv), linededup.line_query(docs)):
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert not any(x in plan for x in ("Python", "Pandas", "Arrow"))


def brute_vectors(rows, threshold):
    ok = {}
    for i, v, lab in rows:
        if lab is not None and v is not None and all(x is not None and np.isfinite(x) for x in v) and any(v):
            ok[i] = (np.array(v) / np.linalg.norm(v), lab)
    links = [(a, b) for a in ok for b in ok if a < b and ok[a][1] == ok[b][1] and float(ok[a][0] @ ok[b][0]) >= threshold]
    n = {i: 0 for i, *_ in rows}
    for a, b in links:
        n[a] += 1
        n[b] += 1
    comp = brute.components([i for i, *_ in rows], links)
    return {i: (n[i], comp[i], comp[i] == i) for i, *_ in rows}


def vectors(seed=1, n=160, dim=12):
    rng = np.random.default_rng(seed)
    base = rng.normal(size=(12, dim))
    out = [(i, [float(x) for x in np.float32(base[i % 12] + rng.normal(scale=0.12 if i % 3 else 0, size=dim))], int(i % 12 % 4)) for i in range(n)]
    return out + [(n, None, 1), (n + 1, [0.0] * dim, 1), (n + 2, [1.0, None], 1), (n + 3, [float("nan")] * dim, 1), (n + 4, [1.0] * dim, None), (n + 5, [], 2), (n + 6, [float("inf")] + [1.0] * (dim - 1), 1)]


@pytest.mark.parametrize("block", [512, 7])
def test_embeddings(spark, block):
    rows = vectors()
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").withColumn("rep", F.lit(1)).withColumn("key", F.lit(1)).repartition(3)
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in embdedup.link_vectors(df, block=block).collect()}
    assert got == brute_vectors(rows, 0.93)
    assert embdedup.link_vectors(df.limit(0)).count() == 0


def test_projections_do_not_depend_on_the_longest_vector():
    p = embdedup.projections(64, 300)
    assert (embdedup.projections(80, 300)[:64] == p).all() and (embdedup.projections(64, 310)[:, :300] == p).all()
    assert abs(p.mean()) < 0.03 and abs(p.std() - 1) < 0.03 and np.abs(np.corrcoef(p) - np.eye(64)).max() < 0.3


def test_embedding_plan_reaches_recall():
    for n in (100, 10**4, 10**7):
        m, tables = embdedup.plan(n)
        p = embdedup.meeting((2 - 2 * 0.93) ** 0.5, embdedup.WIDTH)
        assert 1 - (1 - p**m) ** tables >= 0.999


def test_components(spark):
    rng = random.Random(3)
    edges = [(rng.randrange(400), rng.randrange(400)) for _ in range(280)] + [(k, k + 1) for k in range(1000, 1100)] + [(2000, k) for k in range(2001, 2300)] + [(5000, 5000)]
    got = {r.node: r.comp for r in connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == brute.components({x for e in edges for x in e}, edges)
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_pipeline_stages(spark, sf_dir):
    """Each stage against brute force on its own input."""
    import corpus_pipeline as cp

    from fadedhh.llm import quality

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    columns = docs.columns
    bench = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf_dir}/benchmark.parquet").collect()]
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    assert [n for n, _ in cp.STAGES] == ["quality", "line_dedup", "near_duplicates", "decontamination", "mixing"]
    for name, stage in cp.STAGES:
        out = stage(spark, docs, sf_dir).cache()
        rows = docs.collect()
        before = {r.doc_id: r.text for r in rows}
        after = {r.doc_id: r.text for r in out.collect()}
        if name != "mixing":
            assert out.columns == columns
        if name == "quality":
            model = quality.fit(docs.select("doc_id", "text"), labels.where(~quality.held_out()))
            assert model.rules and set(after) == {i for i, t in before.items() if brute.rule_score(model, t) >= 0.5}
        if name == "line_dedup":
            gone = brute.deleted_lines(list(before.items()))
            left = {i: "\n".join(x for k, x in enumerate((t or "").split("\n")) if k not in gone[i]) for i, t in before.items()}
            assert after == {i: t for i, t in left.items() if not gone[i] or t.strip(" \n\r\t")}
            assert {r.doc_id: r.n_chars for r in out.collect() if gone[r.doc_id]} == {i: len(t) for i, t in after.items() if gone[i]}
        if name == "near_duplicates":
            assert set(after) == {i for i, (_, _, kept) in brute.near(list(before.items())).items() if kept}
        if name == "decontamination":
            assert set(after) == {i for i, w in brute.contaminated(list(before.items()), bench).items() if not w[4]}
        if name == "mixing":
            by = {}
            for r in rows:
                by.setdefault(r.source, []).append(r.doc_id)
            key = {s: f"s:{s}" if s is not None else "n:" for s in by}
            slots = brute.schedule({key[s]: -(-len(x) // 16) for s, x in by.items()}, {key[s]: Fraction(float(len(x)) ** 0.5) for s, x in by.items()})
            place = {i: slots[key[s]][k // 16] for s, x in by.items() for k, i in enumerate(sorted(x, key=lambda i: hashlib.md5(str(i).encode()).hexdigest()))}
            assert after == before and {r.doc_id: r.mix_slot for r in out.collect()} == place
        docs = out


def test_settled_tables_can_be_deleted(spark):
    from fadedhh.llm import common

    df = common.settle(spark.range(3))
    assert df.count() == 3
    common.forget(spark)
    with pytest.raises(Exception):
        spark.read.parquet(df.inputFiles()[0]).count()


def test_pipeline_odd_rows(spark, docs, sf_dir):
    """Nulls, empties, repeats, clashing columns and an empty table: every stage keeps its columns and what it should keep."""
    import corpus_pipeline as cp

    columns = docs.columns
    table = docs.union(docs.where("doc_id in (1, 73)")).union(docs.where("doc_id = 2").withColumn("doc_id", F.lit(None).cast("long")))
    n = table.count()
    for name, stage in cp.STAGES:
        out = stage(spark, table, sf_dir)
        got, had = out.collect(), table.collect()
        assert set(columns) <= set(out.columns) and len(got) <= len(had)
        if name == "quality":
            assert len(got) > n // 2
            out = table  # the model of another table may reject what the next stages are to be tried on
        if name == "line_dedup":
            assert {r.doc_id for r in had if not r.text} <= {r.doc_id for r in got} and sum(len(r.text or "") for r in got) < sum(len(r.text or "") for r in had)
        if name == "near_duplicates":
            kept = {i for i, (_, _, k) in brute.near([(r.doc_id, r.text) for r in had if r.doc_id is not None]).items() if k}
            assert {r.doc_id for r in got} == kept | ({None} if any(r.doc_id is None for r in had) else set())
        if name == "decontamination":
            assert {r.doc_id for r in got} == {r.doc_id for r in had}  # none of these texts is in the benchmark
        if name == "mixing":
            assert sorted(r.mix_order for r in got) == sorted({r.mix_order for r in got}) and len(got) == len(had)
        table = out
    table = docs.limit(0)
    for _, stage in cp.STAGES:
        table = stage(spark, table, sf_dir)
        assert table.count() == 0
