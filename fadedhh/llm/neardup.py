"""Near-duplicate documents by bottom-k sketches of word shingles.

One 63-bit hash per shingle; a document's sketch is its k smallest distinct hashes. Stages:

1. Documents with equal shingle sets form a class; its smallest id stands for it.
2. Inverted lists of retained values count how many classes hold each. Similar sets share at least
   ``least_shared`` of k values (all but one pair in a million), so a class need only be listed under its
   ``k - least_shared + 1`` rarest values: very common passages drop out of the lists by themselves.
3. Classes that share a list get a second, larger sketch of their full sets (most sets fit it whole) and new lists by
   the same rule; what it does not list is done with.
4. Each class meets the most central classes of its new lists; the exact Jaccard of full sets confirms, and confirmed
   links give first components. Groups of copies become one component here, from a linear number of meetings.
5. In lists that still hold several components, classes outside the largest meet members of other components. A pair
   meets in one list only, that of the rarest value both are listed under, where the bound on its overlap by the places of
   that value is exact, and only if the sizes and the bound allow; the values before travel with the lists, so pairs
   that fail are never written. The union-sketch estimate filters and full sets confirm again. No list is cut.
6. Components of all links.
"""

from __future__ import annotations

from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fadedhh.shipping import arrow_map

from . import textbytes as tb
from .common import connected_components, settle

WIDTH = 5
K = 48
K_FULL = 512
HEADS = 3
PERCENT = 75


def least_shared(k: int, percent: int, miss: float = 1e-6) -> int:
    """Largest c such that fewer than c of k sampled union members are shared with probability <= miss."""
    p, total, c = percent / 100, 0.0, 0
    while c < k:
        total += comb(k, c) * p**c * (1 - p) ** (k - c)
        if total > miss:
            break
        c += 1
    return max(1, c)


def shingle_sets(column: pa.Array, width: int = WIDTH, budget: int = 1 << 21):
    """Yields the sorted distinct 63-bit shingle hashes of each row."""
    data, offsets = tb.raw(column)
    for i, j in tb.runs_of_rows(offsets, budget):
        h, count = tb.words(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], tb.SPACED)
        end = np.cumsum(count)
        p = tb.powers(width + 1)
        n = len(h)
        if n >= width:
            s = h[: n - width + 1] * p[1]
            for k in range(1, width):
                s = s + h[k : n - width + 1 + k] * p[k + 1]
            s = tb.mix64(s) >> np.uint64(1)
        for e, c in zip(end.tolist(), count.tolist()):
            if c >= width:
                yield np.unique(s[e - c : e - width + 1])
            elif c:
                yield tb.mix64(np.array([(h[e - c : e] * p[1 : c + 1]).sum() + np.uint64(c)], np.uint64)) >> np.uint64(1)
            else:
                yield np.zeros(0, np.uint64)


def _lists(parts: list[np.ndarray]) -> pa.Array:
    off = np.concatenate([[0], np.cumsum([len(x) for x in parts])]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(off), pa.array(np.concatenate([*parts, np.zeros(0, np.uint64)]).astype(np.int64)))


def sketch_table(docs: DataFrame, doc_id: str, text: str, width: int, k: int) -> DataFrame:
    """(d, n, f1, f2, sk): set size, a 126-bit fingerprint of the set, and the bottom-k sketch."""

    def run(batches):
        for b in batches:
            n, f1, f2, sk = [], [], [], []
            for u in shingle_sets(b.column(1), width):
                n.append(len(u))
                f1.append(int((tb.mix64(u + np.uint64(3)) >> np.uint64(20)).sum() & np.uint64((1 << 62) - 1)))
                f2.append(int(np.bitwise_xor.reduce(tb.mix64(u + np.uint64(9))) >> np.uint64(1)) if len(u) else 0)
                sk.append(u[:k].copy())  # a view would keep the whole set alive
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(f1, pa.int64()), pa.array(f2, pa.int64()), _lists(sk)], names=["d", "n", "f1", "f2", "sk"])

    rows = docs.select(F.col(doc_id).cast("long").alias("d"), F.col(text).alias("t"))
    return arrow_map(rows, run, "d long, n long, f1 long, f2 long, sk array<long>")


def full_sets(docs: DataFrame, wanted: DataFrame, doc_id: str, text: str, width: int) -> DataFrame:
    """(d, n, st) of the wanted ids only; repeated rows repeat, which changes no link."""

    def run(batches):
        for b in batches:
            off = tb.raw(b.column(1))[1]
            for i, j in tb.runs_of_rows(off, 1 << 20):
                sets = list(shingle_sets(b.column(1).slice(i, j - i), width))
                yield pa.RecordBatch.from_arrays([b.column(0).slice(i, j - i), pa.array([len(u) for u in sets], pa.int64()), _lists(sets)], names=["d", "n", "st"])

    rows = docs.select(F.col(doc_id).cast("long").alias("d"), F.col(text).alias("t")).join(wanted.select(F.col("rep").alias("d")).hint("merge"), "d", "left_semi")
    return arrow_map(rows, run, "d long, n long, st array<long>")


def _listing(sketches: DataFrame, shared: DataFrame, k: int, percent: int) -> DataFrame:
    """(rep, n, size, c, pv): per class the shared values it is listed under, rarest first, its ``size`` sketch values and
    how many of those are shared at all. ``shared`` has (v, df), df > 1.

    A set of at most k * percent / 100 values and every similar one lie whole in their sketches: there the overlap
    needed is exact. Else it is the sampled one, or the exact one where that is smaller.
    """
    need = least_shared(k, percent)
    hits = sketches.select("rep", F.explode("sk").alias("v")).join(shared.hint("merge"), "v")
    lists = hits.groupBy("rep").agg(F.sort_array(F.collect_list(F.struct("df", "v"))).alias("dv"))
    both = lists.join(sketches.select("rep", "n", F.size("sk").alias("size")).hint("merge"), "rep")
    overlap = F.when(F.col("n") <= k * percent // 100, F.ceil(F.col("n") * percent / 100)).otherwise(F.least(F.lit(need), F.ceil(F.col("n") * percent / 100)))
    both = both.withColumn("c", F.size("dv")).withColumn("spare", (F.col("c") - overlap + 1).cast("int")).where("spare > 0")
    return both.select("rep", "n", "size", "c", F.transform(F.slice("dv", F.lit(1), F.greatest("spare", F.lit(0))), lambda x: x["v"]).alias("pv"))


def _estimate_ok(sa: str, sb: str, k: int, need: int, percent: int):
    """Union-sketch estimate: of the k smallest values of both sketches, how many lie in both."""
    both = F.array_intersect(sa, sb)
    union = F.slice(F.sort_array(F.array_union(sa, sb)), 1, k)
    shared = F.size(F.array_intersect(both, union))
    return F.when(F.size(union) < k, F.size(both) * 100 >= percent * F.size(union)).otherwise(shared >= need)


def _confirm(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) whose full sets reach the similarity."""
    left = sets.select(F.col("d").alias("a"), F.col("n").alias("na"), F.col("st").alias("sa"))
    right = sets.select(F.col("d").alias("b"), F.col("n").alias("nb"), F.col("st").alias("sb"))
    both = pairs.join(left.hint("merge"), "a").join(right.hint("merge"), "b")
    both = both.withColumn("x", F.size(F.array_intersect("sa", "sb")).cast("long"))
    return both.where(F.col("x") * 100 >= percent * (F.col("na") + F.col("nb") - F.col("x"))).select("a", "b")


def near_duplicates(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", width: int = WIDTH, percent: int = PERCENT, k: int = K, k_full: int = K_FULL) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for every row.

    Documents shorter than the shingle width count their whole sequence as one shingle; null texts and texts
    without words have no shingle and link with nothing. Rows that repeat an id come out once each. A row without id
    takes the component of its class, or null. Two sets are told apart by 126 bits, shingles by 63.
    """
    d = settle(sketch_table(docs, doc_id, text, width, k))
    classes = settle(d.where("n > 0 and d is not null").groupBy("n", "f1", "f2").agg(F.min("d").alias("rep"), F.first("sk").alias("sk")))
    count = lambda sketches: settle(sketches.select(F.explode("sk").alias("v")).groupBy("v").agg(F.count("*").alias("df")).where("df > 1"))
    listed = settle(_listing(classes, count(classes), k, percent))
    lists = listed.select("rep", F.explode("pv").alias("v"))
    heads = settle(lists.groupBy("v").agg(F.count("*").alias("m")).where("m > 1").select("v"))
    sets = settle(full_sets(docs, settle(lists.join(heads.hint("merge"), "v").select("rep").distinct()), doc_id, text, width))

    large = sets.select(F.col("d").alias("rep"), "n", F.slice("st", 1, k_full).alias("sk"))
    wide = settle(_listing(large, count(large), k_full, percent))
    lists = wide.select("rep", "size", "c", F.explode("pv").alias("v"))
    rank = F.struct(F.floor(F.col("c") * 1000 / F.col("size")).alias("c"), (-F.col("rep")).alias("r"))
    heads = settle(lists.groupBy("v").agg(F.count("*").alias("m"), F.max(rank).alias("h")).where("m > 1").select("v", (-F.col("h.r")).alias("head")))
    meet = lists.join(heads.hint("merge"), "v").where("rep <> head").groupBy("rep", "head").agg(F.count("*").alias("m"))
    best = meet.groupBy("rep").agg(F.slice(F.sort_array(F.collect_list(F.struct((-F.col("m")).alias("m"), "head"))), 1, HEADS).alias("h"))
    best = settle(best.select(F.col("rep").alias("a"), F.explode(F.transform("h", lambda x: x["head"])).alias("b")))
    first = settle(_confirm(best, sets, percent))
    comp = connected_components(first).select(F.col("node").alias("rep"), "comp")

    short = settle(wide.join(comp.hint("merge"), "rep", "left").withColumn("comp", F.coalesce("comp", "rep")))
    groups = short.select("comp", F.explode("pv").alias("v")).groupBy("v", "comp").agg(F.count("*").alias("m"))
    mixed = settle(groups.groupBy("v").agg(F.count("*").alias("kinds"), F.max(F.struct("m", "comp")).alias("big")).where("kinds > 1").select("v", F.col("big.comp").alias("big")))
    full = short.select("rep", "comp", "n", "size", "c", "pv", F.posexplode("pv").alias("i", "v"))
    placed = full.select("v", "rep", "comp", "n", (F.col("size") - F.col("c") + F.col("i")).alias("at"), "size", F.expr("slice(pv, 1, i)").alias("pre"))
    open_ = settle(placed.join(mixed.hint("merge"), "v"))
    side = lambda p: [F.col(x).alias(f"{x}_{p}") for x in ("rep", "comp", "n", "at", "size", "pre")]
    apart = (F.col("comp_a") != F.col("comp_b")) & ((F.col("comp_b") == F.col("big")) | (F.col("rep_a") < F.col("rep_b")))
    sizes = (F.col("n_a") * 100 >= percent * F.col("n_b")) & (F.col("n_b") * 100 >= percent * F.col("n_a"))
    whole = (F.col("n_a") <= k_full) & (F.col("n_b") <= k_full)
    needed = F.when(whole, (F.col("n_a") + F.col("n_b")) * percent / (100 + percent)).otherwise(F.lit(float(least_shared(k_full, percent))))
    room = F.least(F.col("size_a") - F.col("at_a"), F.col("size_b") - F.col("at_b")) >= needed - 1e-9
    once = ~F.arrays_overlap("pre_a", "pre_b")
    outside = open_.where("comp <> big").select("v", *side("a"))
    pairs = outside.join(open_.select("v", "big", *side("b")).hint("merge"), "v").where(apart & sizes & room & once).select(F.col("rep_a").alias("a"), F.col("rep_b").alias("b"))
    sk = classes.select("rep", "sk")
    pairs = settle(pairs).join(sk.select(F.col("rep").alias("a"), F.col("sk").alias("sa")).hint("merge"), "a").join(sk.select(F.col("rep").alias("b"), F.col("sk").alias("sb")).hint("merge"), "b")
    pairs = pairs.where(_estimate_ok("sa", "sb", k, least_shared(k, percent), percent)).select("a", "b")
    second = settle(_confirm(settle(pairs), sets, percent))
    final = connected_components(first.union(second)).select(F.col("node").alias("rep"), "comp")
    place = settle(classes.select("n", "f1", "f2", "rep").join(final, "rep", "left").select(F.col("n").alias("cn"), F.col("f1").alias("c1"), F.col("f2").alias("c2"), F.coalesce("comp", "rep").alias("comp")))
    res = d.select("d", "n", "f1", "f2").join(place.hint("merge"), F.expr("n = cn and f1 = c1 and f2 = c2"), "left")
    component = F.coalesce("comp", "d")
    return res.select(F.col("d").alias("doc_id"), F.col("n").alias("n_shingles"), component.alias("component_id"), F.coalesce(F.col("d") == component, F.lit(False)).alias("kept"))


ORACLE = """
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') AS ws FROM documents),
s AS (SELECT DISTINCT doc_id, unnest(CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 5 THEN [array_to_string(ws, ' ')]
        ELSE list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i + 4], ' ')) END) AS g FROM w),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS x FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY ALL),
l AS (SELECT a, b FROM p JOIN n u ON u.doc_id = a JOIN n v ON v.doc_id = b WHERE 100 * x >= 75 * (u.n + v.n - x)),
r AS (SELECT doc_id AS node, doc_id AS seen FROM documents UNION SELECT r.node, l.b FROM r JOIN l ON r.seen = l.a)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, m.c AS component_id, m.c = d.doc_id AS kept
FROM documents d LEFT JOIN n ON n.doc_id = d.doc_id JOIN (SELECT node, min(seen) AS c FROM r GROUP BY node) m ON m.node = d.doc_id
"""
