"""Operators on documents against brute force, on a small table with every odd case."""

import random

import brute
import pytest
from support import compare
from pyspark.sql import functions as F

from fadedhh.llm import decontam, langid, linededup, maxent, neardup, quality, registry, suffixdedup


def pairs(rows):
    return [(r[0], r[1]) for r in rows]


def by_id(df, *cols):
    return {r[0]: tuple(r[1:]) for r in df.select(df.columns[0], *cols).collect()}


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_registered_sql(spark, sf_dir, name):
    got, want = compare(spark, registry.queries()[name], registry.oracle_sql()[name], sf_dir)
    assert got == want


def test_near_duplicates(docs, rows):
    got = by_id(neardup.near_duplicates(docs), "n_shingles", "component_id", "kept")
    assert got == brute.near(pairs(rows))


def test_near_duplicates_with_tiny_sketches_lists_all(docs, rows):
    """Sketches too small for the sets still lose no clear copy."""
    got = by_id(neardup.near_duplicates(docs, k=16, k_full=32), "component_id")
    want = brute.near(pairs(rows), 90)
    assert all(got[i][0] <= c for i, (_, c, _) in want.items())


def test_near_copies_in_one_large_group(spark):
    rng = random.Random(7)
    base = [f"w{rng.randrange(400)}" for _ in range(120)]
    rows = []
    for i in range(150):
        w = list(base)
        for _ in range(rng.randrange(0, 9)):
            w[rng.randrange(len(w))] = f"e{rng.randrange(10**6)}"
        rows.append((i, " ".join(w)))
    got = by_id(neardup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")), "n_shingles", "component_id", "kept")
    assert got == brute.near(rows)


def test_near_duplicates_nulls_repeats_and_empty(spark, empty):
    rows = [(1, "a b c d e f g"), (1, "a b c d e f g"), (2, "A b c d e f g"), (None, "a b c d e f g"), (3, None)]
    got = sorted(map(tuple, neardup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()), key=str)
    assert got == sorted([(1, 3, 1, True), (1, 3, 1, True), (2, 3, 1, False), (None, 3, 1, False), (3, 0, 3, True)], key=str)
    assert neardup.near_duplicates(empty).count() == 0


def test_contamination(spark, docs, rows):
    bench = [(1, " ".join(rows[0][1].split()[:20])), (2, "Zuq, vexi!"), (3, ""), (4, None), (None, "the of"), (5, rows[5][1]), (5, "is that it"), (10, " ".join(rows[5][1].split()[-14:]))]
    b = spark.createDataFrame(bench, "item_id long, text string")
    want = brute.contaminated(pairs(rows), [x for x in bench if x[0] is not None])
    assert by_id(decontam.decontam_query(docs, b), "n_words", "n_hit", "n_items", "items_sha256", "contaminated") == want
    several = decontam.verdicts(docs, b, pass_bytes=300)
    assert by_id(several, "n_words", "n_hit", F.size("items"), "contaminated") == {i: (w[0], w[1], w[2], w[4]) for i, w in want.items()}


def test_contamination_with_empty_tables(spark, docs, empty):
    none = spark.createDataFrame([], "item_id long, text string")
    assert decontam.decontam_query(docs, none).where("n_hit > 0 or contaminated").count() == 0
    assert decontam.decontam_query(empty, none).count() == 0


@pytest.mark.parametrize("hot", [200_000, 0])
def test_repeats(docs, rows, hot):
    """Also with every anchor dealt window by window, and many blocks."""
    out = suffixdedup.remove_repeats(docs, hot=hot, block_bytes=2000)
    got = by_id(out, "n_bytes", "n_removed", F.size("starts"), F.sha2("kept", 256))
    assert got == brute.repeats(pairs(rows))


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_repeats_on_hard_strings(spark, seed):
    rng = random.Random(seed)
    a = "".join(rng.choice("ab") for _ in range(260))
    rows = [(0, "x" * 350), (1, a), (2, a[:99]), (3, a[40:] + a[:140]), (4, "x" * 100), (5, a), (6, ("xy" * 90) + a[100:215]), (7, None), (8, "é" * 60 + a[10:130])]
    rows += [(10 + k, "".join(rng.choice([a[rng.randrange(200) :][: rng.randrange(1, 180)], "q" * rng.randrange(130)]) for _ in range(3))) for k in range(12)]
    got = by_id(suffixdedup.substring_query(spark.createDataFrame(rows, "doc_id long, text string").repartition(3)), "n_bytes", "n_removed", "n_spans", "kept_sha256")
    assert got == brute.repeats(rows)


def test_repeats_nulls_repeats_and_empty(spark, empty):
    t = "z" + "ab" * 60
    out = suffixdedup.substring_query(spark.createDataFrame([(5, t), (5, t), (None, t), (6, "short")], "doc_id long, text string"))
    got = sorted(((r.doc_id, r.n_bytes, r.n_removed) for r in out.collect()), key=str)
    assert [g for g in got if g[0] == 5] == [(5, 121, 121)] * 2 and [g[0] for g in got].count(None) == 1
    assert suffixdedup.substring_query(empty).count() == 0


def test_line_dedup_edges(spark, empty):
    p, q = "p" * 130, "q" * 70
    rows = [(1, f"{p}\nx\n{q}\n{q}"), (2, f"y\n{q}\n{q}\nz"), (3, f"{q}\ny\n{q}"), (4, None), (5, ""), (6, "\n" * 400), (7, "\n" * 400), (2, f"y\n{q}\n{q}\nz"), (None, p)]
    out = linededup.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string"))
    got = sorted(((r.doc_id, r.text, r.ld_removed) for r in out.collect()), key=str)
    want = [(1, f"x\n{q}\n{q}", 1), (2, "y\nz", 2), (2, "y\nz", 2), (3, f"{q}\ny\n{q}", 0), (4, None, 0), (5, "", 0), (6, "\n" * 400, 0), (7, "\n" * 400, 0), (None, p, 0)]
    assert got == sorted(want, key=str)
    assert linededup.line_query(empty).count() == 0


def test_line_dedup_finds_runs_of_any_number_of_lines(spark):
    """Many short lines, blank lines between, and the short tail of a run: none fits six lines."""
    short = "\n".join(f"w{k} v{k}" for k in range(60))
    gaps = "\n\n\n".join(f"part {k} of the passage" for k in range(9))
    tail = "\n".join(["z" * 200, *(f"tail {k:05d}" for k in range(8))])
    rows = [(2 * k + j, f"{'ab'[j] * 5}{k}\n{t}\n{'cd'[j] * 5}{k}") for k, t in enumerate((short, gaps, tail)) for j in (0, 1)]
    got = {r.doc_id: (r.text, r.ld_removed) for r in linededup.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    for k, t in enumerate((short, gaps, tail)):
        assert got[2 * k] == (rows[2 * k][1], 0) and got[2 * k + 1] == (f"bbbbb{k}\nddddd{k}", t.count("\n") + 1)


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_line_dedup_against_brute_force(spark, seed):
    """Few kinds of lines, so that runs overlap, repeat within a text and end at blank lines."""
    rng = random.Random(seed)
    kinds = ["", "", "a", "bb", "c" * 30, "d" * 50, "e" * 130, "f f f f", "g" * 90]
    runs = [[rng.choice(kinds) for _ in range(rng.randrange(2, 14))] for _ in range(8)]
    rows = []
    for i in range(60):
        ls = [x for _ in range(rng.randrange(1, 5)) for x in (rng.choice(runs) if rng.random() < 0.7 else [rng.choice(kinds) for _ in range(3)])]
        rows.append((i, "\n".join(ls)))
    rows.append((60, "\n".join(["ab"] * 300)))
    gone = brute.deleted_lines(rows)
    out = linededup.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string").repartition(3)).collect()
    assert {r.doc_id: (r.text, r.ld_removed) for r in out} == {i: ("\n".join(x for k, x in enumerate(t.split("\n")) if k not in gone[i]), len(gone[i])) for i, t in rows}


def test_language_against_brute_force(docs, rows):
    """Prototypes and cosines from vectors bound and bundled letter by letter."""
    import numpy as np

    vector = lambda p, seen={}: seen.setdefault(p, langid.letter_vectors(np.array([p]))[0].astype(float))  # noqa: E731, B006
    texts = brute.hypervectors([r[1] for r in rows], langid.DIM, vector)
    total = {}
    for (i, _, lang, *_), v in zip(rows, texts):
        if lang and not brute.held(i, 4, 2):
            total[lang] = total.get(lang, 0) + v
    got = {r.doc_id: r for r in langid.language_id(docs).collect()}
    for (i, *_), v in zip(rows, texts):
        if np.abs(v).sum():
            cos = {x: v @ t / np.linalg.norm(v) / np.linalg.norm(t) for x, t in total.items()}
            assert abs(got[i].score - min(1, max(0, max(cos.values())))) < 1e-5 and cos[got[i].lang_pred] > max(cos.values()) - 1e-9


def test_language_of_a_long_text_in_pieces():
    import numpy as np

    text = "Ab, c  dé.\n" * 900
    whole, n = langid.bundles([text], np.zeros(1, np.int64), 1)
    parts, m = langid.bundles([text], np.zeros(1, np.int64), 1, piece=257)
    assert n[0] == m[0] and np.allclose(whole, parts)


def test_texts_of_several_megabytes(spark):
    """One text of 3 MB beside short ones goes through every operator on texts, whole."""
    rng = random.Random(4)
    big = "\n".join(" ".join(f"w{rng.randrange(50000)}" for _ in range(40)) for _ in range(11000))
    rows = [(0, big, "en"), (1, big[:-200], "en"), (2, "a short one of its own", "en"), (3, big[1_000_000:1_000_900], None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    assert {r.doc_id: r.lang_pred for r in langid.language_id(df).collect()}[0] in ("en", "und")
    assert {r.doc_id: r.component_id for r in neardup.near_duplicates(df).collect()} == {0: 0, 1: 0, 2: 2, 3: 3}
    assert {r.doc_id: r.n_tokens for r in maxent.lm_scores(df).collect()} == {i: len(t.split()) + 1 for i, t, _ in rows}
    got = {r.doc_id: r for r in suffixdedup.substring_query(df).collect()}
    assert got[0].n_removed < 3000 and got[1].n_removed >= len(rows[1][1]) - 1 and got[3].n_removed == 900
    gone = brute.deleted_lines([r[:2] for r in rows])
    assert {r.doc_id: r.ld_removed for r in linededup.dedup_lines(df).collect()} == {i: len(x) for i, x in gone.items()}
    bench = spark.createDataFrame([(7, rows[3][1])], "item_id long, text string")
    assert {r.doc_id: (r.n_words, r.n_hit) for r in decontam.decontam_query(df, bench).collect()} == {d: x[:2] for d, x in brute.contaminated([r[:2] for r in rows], [(7, rows[3][1])]).items()}


def test_language(docs, rows, empty):
    got = {r.doc_id: r for r in langid.language_id(docs).collect()}
    assert len(got) == len(rows)
    right = [got[i].lang_pred == lang for i, t, lang, *_ in rows if lang and t and len(t) > 60 and i < 60]
    assert sum(right) / len(right) > 0.97
    for i, t, *_ in rows:
        r = got[i]
        assert 0 <= r.score <= 1 and (r.lang_pred == "und") == (not any(c.isalpha() for c in t or ""))
    assert langid.language_id(empty).count() == 0


def test_language_without_training_labels(docs):
    out = langid.language_id(docs.withColumn("lang", F.lit(None).cast("string")))
    assert {r.lang_pred for r in out.collect()} == {"und"}


def test_trigram_vectors_are_nearly_orthogonal():
    import numpy as np

    codes = np.array([(a << 42) | (b << 21) | c for a in (97, 98) for b in (99, 100) for c in (101, 102)], np.uint64)
    v = langid.trigram_vectors(codes).astype(int)
    gram = v @ v.T / langid.DIM
    assert np.allclose(np.diag(gram), 1) and np.abs(gram - np.eye(8)).max() < 0.15
    assert (langid.trigram_vectors(np.array([(97 << 42) | (98 << 21) | 99], np.uint64)) != langid.trigram_vectors(np.array([(98 << 42) | (97 << 21) | 99], np.uint64))).any()


def test_lm_base_scores(docs, rows, empty):
    got = {r.doc_id: r for r in maxent.lm_scores(docs).collect()}
    for i, (held, n, known, total, base) in brute.base_scores(pairs(rows)).items():
        r = got[i]
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (held, n, known, total)
        assert abs(r.base_score - base) < 1e-6 * max(1, abs(base)) and r.score < 0
    assert maxent.lm_scores(empty).count() == 0


def lm_parts(spark, rows):
    """Counts, model and pairs learnt from the rows that are not held out."""
    table = spark.createDataFrame(rows, "doc_id long, text string").where("crc32(cast(doc_id as string)) % 7 <> 2")
    counts = maxent.Counts(table, "text")
    return counts, *maxent.train_model(table, counts, "text", "doc_id")


def lm_brute(counts, model, pairs, train):
    """(words before, word) -> probability, from loops over outputs, classes, members and counted pairs."""
    import numpy as np

    book = counts.book
    place = {int(w): k for k, w in enumerate(book.word)}
    output = lambda h: int(book.output[place[h]]) if h in place else 0
    count = lambda h: int(book.count[place[h]]) if h in place else 0
    pair = {}
    for ws in train:
        for a, b in zip([0, *ws], ws):
            if b in place and output(b) < maxent.GROUPS:
                pair[a, b] = pair.get((a, b), 0) + 1

    def softmax(z):
        z = np.exp(z - z.max())
        return z / z.sum()

    def probability(two, one, word):
        o1, o2 = (maxent.START_ID if x == 0 else output(x) for x in (one, two))
        f = maxent.features(np.array([o1]), np.array([o2]))[:, 0]
        o = output(word)
        p = softmax(sum(model.of_class[k].astype(float) for k in f))[o // maxent.MEMBERS]
        p *= softmax(sum(model.of_member[k * maxent.CLASSES + o // maxent.MEMBERS].astype(float) for k in f))[o % maxent.MEMBERS]
        if o < maxent.GROUPS:
            inside = {k: n for k, n in pair.items() if k[0] == one and output(k[1]) == o}
            u, n = (count(word) + 1) / book.mass[o], sum(inside.values())
            p *= (inside.get((one, word), 0) + len(inside) * u) / (n + len(inside)) if inside else u
        return p

    return probability


def test_lm_scores_against_brute_force(spark, docs, rows):
    """Every score is the sum of the logarithms of a softmax worked out output by output, and probabilities sum to 1."""
    import numpy as np
    import pyarrow as pa

    few = [r for r in pairs(rows) if len(r[1] or "") < 3000]
    counts, model, kept = lm_parts(spark, few)
    toks = {i: [int(x) for x in next(maxent.tokens(pa.array([t or ""])))[1]] for i, t in few}
    held = {i: brute.held(i, 7, 2) for i, _ in few}
    p = lm_brute(counts, model, kept, [toks[i] for i, _ in few if not held[i]])
    lm = spark.createDataFrame([(i, t, held[i]) for i, t in few], "doc_id long, text string, held boolean")
    got = {r.doc_id: r.score for r in maxent.score_texts(lm, counts, model, kept, "text", "doc_id", "held").collect()}
    for i, ws in list(toks.items())[::5]:
        want = sum(np.log10(p(a, b, w)) for a, b, w in zip([0, 0, *ws], [0, *ws], ws))
        assert abs(got[i] - want) < 1e-4 * max(1, abs(want))
    for a, b in ((0, 0), (0, toks[1][0]), tuple(toks[1][3:5]), tuple(toks[7][-3:-1])):
        assert abs(sum(p(a, b, int(w)) for w in counts.book.word) + p(a, b, -5) - 1) < 1e-4


def test_lm_keeps_the_commonest_pairs(spark):
    rows = [(i, " ".join(f"w{j} v{j}" for j in range(700) if j % (1 + i // 2) == 0)) for i in range(8)]
    table = spark.createDataFrame(rows, "doc_id long, text string")
    counts = maxent.Counts(table, "text")
    held = spark.sparkContext.broadcast(counts.book)
    every, few = maxent.count_pairs(table, held, "text"), maxent.count_pairs(table, held, "text", limit=400)
    assert 0 < len(few.key) <= 400 < len(every.key) and min(few.n) > 1 and (every.n >= min(few.n)).sum() == len(few.key)
    assert (every.kept < every.total).all() and set(few.context) <= set(every.context)


def test_lm_scores_do_not_depend_on_the_pairs_held(spark):
    """Pairs and contexts beyond the limit get their weights by the join, in repeated rows too."""
    import numpy as np
    import pyarrow as pa

    few = [(i, " ".join(f"w{j} v{j % (50 * i + 1)}" for j in range(700) if j % (1 + i // 2) == 0)) for i in range(10)]
    counts, model, every = lm_parts(spark, few)
    table = spark.createDataFrame(few, "doc_id long, text string").where("crc32(cast(doc_id as string)) % 7 <> 2")
    held = spark.sparkContext.broadcast(counts.book)
    lm = spark.createDataFrame([(i, t, False) for i, t in [*few, few[3], (None, few[5][1])]], "doc_id long, text string, held boolean").repartition(3)
    score = lambda p: sorted((r.doc_id is None, r.doc_id, r.n_known, round(r.score, 6)) for r in maxent.score_texts(lm, counts, model, p, "text", "doc_id", "held").collect())
    want = score(every)
    for limit in (0, 400):
        some = maxent.count_pairs(table, held, "text", limit=limit, portion=500)
        assert len(some.key) <= limit < len(every.key) and score(some) == want
    toks = {i: [int(x) for x in next(maxent.tokens(pa.array([t])))[1]] for i, t in few}
    p = lm_brute(counts, model, every, [toks[i] for i in toks if not brute.held(i, 7, 2)])
    got = {r[1]: r[3] for r in want}
    for i in (4, 9):
        brute_score = sum(np.log10(p(a, b, w)) for a, b, w in zip([0, 0, *toks[i]], [0, *toks[i]], toks[i]))
        assert abs(got[i] - brute_score) < 1e-4 * abs(brute_score)


def test_lm_broadcasts_hold_keys_and_counts_alone():
    """Every executor has its broadcasts on disk: 18 bytes a word, 12 a pair and 24 a context, and what finds them is made there."""
    import pickle

    import numpy as np

    rng = np.random.default_rng(3)
    key = np.unique(rng.integers(0, 1 << 62, 60000))
    n = np.arange(1, len(key) + 1)
    book = maxent.Dictionary(key.view(np.uint64), n[::-1].copy(), True, 1, 1)
    before, at = np.unique(key >> 18, return_index=True)
    pairs = maxent.Pairs(key, n, before, n[at] + 1.0, n[at] + 0.0)
    ask = np.concatenate([key[::7], key[::5] + 1, [0, -1]])
    u = np.full(len(ask), 0.25)
    want = book.find(ask.view(np.uint64)), pairs(ask, u), pairs.missing(ask)
    assert (want[0][: len(key[::7])] == np.arange(len(key))[::7]).all() and (want[0][-2:] == -1).all()
    for x, least in ((book, 18 * len(key)), (pairs, 12 * len(key) + 24 * len(before))):
        assert len(pickle.dumps(x)) < 1.05 * least + 10000
    book, pairs = pickle.loads(pickle.dumps((book, pairs)))
    assert all((a == b).all() for a, b in zip(want, (book.find(ask.view(np.uint64)), pairs(ask, u), pairs.missing(ask))))


def test_lm_lets_its_broadcasts_go(spark, docs, monkeypatch):
    """Of all that training broadcasts, nothing stays on disk; the tables of the scores do."""
    import os

    made, plain = [], type(spark.sparkContext).broadcast
    monkeypatch.setattr(type(spark.sparkContext), "broadcast", lambda self, x: made.append(plain(self, x)) or made[-1])
    out = maxent.lm_scores(docs)
    assert len(made) > 3 and [os.path.exists(b._path) for b in made] == [False] * (len(made) - 1) + [True]
    assert out.count() == docs.count()


def test_lm_softmax_stays_in_range():
    """Lines far from 0 give the same probabilities as those near it."""
    import numpy as np

    w = np.random.default_rng(5).normal(0, 3, (4, 32)).astype(np.float32)
    rows = np.zeros((4, 2), np.int64) + np.arange(4)[:, None]
    z, e, total = maxent._softmax(w, rows)
    for far in (300, -300):
        fz, fe, ftotal = maxent._softmax(w + np.float32(far) * np.eye(4, dtype=np.float32)[:, :1], rows)
        assert np.allclose(fe / ftotal[:, None], e / total[:, None], rtol=1e-3) and np.allclose(np.exp(fz) / ftotal[:, None], e / total[:, None], rtol=1e-3)


def test_word_hashes_do_not_depend_on_the_length(monkeypatch):
    import numpy as np
    import pyarrow as pa

    from fadedhh.llm import textbytes as tb

    data, offsets = tb.raw(pa.array(["Ab cd", "", None, "x", "yé  Z\n", " ", "abc" * 90]))
    near = tb.words(data, offsets, tb.SPACED)
    monkeypatch.setattr(tb, "NEAR", 0)
    far = tb.words(data, offsets, tb.SPACED)
    assert (near[0] == far[0]).all() and near[1].tolist() == far[1].tolist() == [2, 0, 0, 1, 2, 0, 1] and len(np.unique(near[0])) == 6


def test_lm_counts_beyond_the_dictionary(spark, docs, rows, monkeypatch):
    """Words that the dictionary does not hold come by the join."""
    monkeypatch.setattr(maxent, "DICTIONARY", 5)
    got = {r.doc_id: r for r in maxent.lm_scores(docs).collect()}
    for i, (_, n, known, _, base) in brute.base_scores(pairs(rows)).items():
        assert got[i].n_known == known and abs(got[i].base_score - base) < 1e-6 * max(1, abs(base))


def test_lm_is_a_distribution_and_learns():
    import numpy as np

    rng = np.random.default_rng(0)
    ids = np.tile([3, 40, 77, 500], 4000)
    ids[rng.random(len(ids)) < 0.1] = 0
    count = np.full(len(ids) // 16, 16)
    one, two = maxent.history(ids, count)
    m = maxent.Model.from_counts(np.bincount(ids, minlength=maxent.OUTPUTS).astype(float))
    before = m.score(ids, one, two).mean()
    squares = maxent.Model(np.zeros_like(m.w))
    for lo in range(0, len(ids), 2000):
        part = slice(lo, lo + 2000)
        m.update(ids[part], one[part], two[part], squares, 0.25)
    assert m.score(ids, one, two).mean() > before + 0.5
    every = np.arange(maxent.OUTPUTS)
    p = np.exp(m.score(every, np.full(len(every), 3), np.full(len(every), 40)))
    assert abs(p.sum() - 1) < 1e-4


def test_quality(spark, docs, rows, empty):
    """Loud rows are bad: held-out ones are told apart, and empty texts get a score."""
    rng = random.Random(2)
    loud = [(1000 + k, " | ".join("#$%" * rng.randrange(1, 4) for _ in range(rng.randrange(5, 60))), "en", "s", 1) for k in range(60)]
    table = docs.select("doc_id", "text").union(spark.createDataFrame(loud, docs.select("doc_id", "text", "lang", "source", "n_chars").schema).select("doc_id", "text"))
    labels = spark.createDataFrame([(r[0], 1) for r in rows[:60]] + [(r[0], 0) for r in loud] + [(None, 1), (5, 1), (77777, 0), (4, None)], "doc_id long, quality int")
    out = {r.doc_id: r for r in quality.quality_query(table, labels).collect()}
    assert len(out) == len(rows) + 60 and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.5) for r in out.values())
    held = [(r.predicted == (0 if i >= 1000 else 1)) for i, r in out.items() if r.held_out and (i >= 1000 or i < 60)]
    assert sum(held) / len(held) > 0.95
    none = spark.createDataFrame([], "doc_id long, quality int")
    assert {r.score for r in quality.quality_query(table, none).collect()} == {0.5}
    assert quality.quality_query(empty, labels).count() == 0


def test_rule_model_column_equals_rules(spark):
    m = quality.RuleModel(0.5, [((("a", True, 1.0), ("b", False, 2.0)), 1.5), ((("a", False, 1.0),), -2.0)])
    df = spark.createDataFrame([(0.0, 3.0), (2.0, 2.0), (2.0, 2.5)], "q_a double, q_b double")
    got = [r[0] for r in df.select(m.column()).collect()]
    assert [round(g, 6) for g in got] == [round(1 / (1 + 2.718281828459045**-z), 6) for z in (-1.5, 2.0, 0.5)]
