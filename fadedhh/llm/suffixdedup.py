"""Exact substring deduplication with longest-previous-factor arrays.

A byte goes if a 100-byte string that covers it also starts earlier (smaller id, or earlier in the same document).

1. Winnowed anchors: in every 100-byte window the 32-byte gram of smallest hash. Equal windows have equal
   anchors at equal offsets, so only anchors found in two different texts, or twice in one, matter.
   Counting is one shuffle of (anchor, block) rows, pre-aggregated per batch.
2. Each block of documents gets its repeated anchors back and cuts the context of each: the windows that chose it
   (up to 168 bytes). Equal contexts of a block travel once; the later ones are covered whole.
3. Contexts meet by anchor. Equal ones again leave the first; the rest go through suffix arrays: suffixes sort
   by their first 100 bytes, previous and next smaller positions in that order give the earlier match of
   each, and windows with one are marked. An anchor with very many contexts sends its windows one by one,
   dealt by their first and last grams as well, so that no task holds them all.
4. Whole copies of a text are told by its hash and go whole. Marks return to their block and are merged.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from fadedhh.shipping import arrow_map

from . import textbytes as tb
from .common import settle

LENGTH = 100
GRAM = 32
BLOCK_BYTES = 6 << 20
#: Occurrences from which an anchor's contexts are dealt window by window.
HOT = 200_000
_MIN = np.iinfo(np.int64).min
_SCHEMA = "kind int, fp long, cx long, d long, th long, s long, e long, ctx binary"


_inverse = np.ones(1, np.uint64)


def inverse_powers(n: int) -> np.ndarray:
    """Powers of the inverse of the hash base modulo 2**64."""
    global _inverse
    if len(_inverse) < n:
        p = np.full(max(n, 4096, 2 * len(_inverse)), np.uint64(pow(int(tb.powers(2)[1]), -1, 1 << 64)))
        p[0] = 1
        _inverse = np.multiply.accumulate(p)
    return _inverse[:n]


class Rolling:
    """Hashes of any substrings of a byte string, by prefix sums."""

    def __init__(self, data: np.ndarray):
        n = len(data)
        self.sum = np.concatenate([np.zeros(1, np.uint64), np.cumsum(tb.BYTE_CODE[data] * tb.powers(n + 1)[:n], dtype=np.uint64)])
        self.back = inverse_powers(n + 1)

    def of(self, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
        return tb.mix64((self.sum[end] - self.sum[begin]) * self.back[begin] + (end - begin).astype(np.uint64))


def _slide(x: np.ndarray, width: int) -> np.ndarray:
    """Minimum of every window of ``width``."""
    span = 1
    while span < width:
        step = min(span, width - span)
        x = np.minimum(x[:-step], x[step:]) if len(x) > step else x[:0]
        span += step
    return x


def anchors(data: np.ndarray, offsets: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, ...]:
    """(gram hash, row, first window, last window, hasher) of the winnowed grams: each ``length``-byte window of a row
    belongs to its leftmost gram of smallest hash, and the windows of a gram are consecutive starts."""
    roll = Rolling(data)
    n, width = len(data), length - gram + 1
    none = np.zeros(0, np.int64)
    if n < length:
        return np.zeros(0, np.uint64), none, none, none, roll
    at = np.arange(n - gram + 1)
    g = roll.of(at, at + gram)
    low = _slide((g & np.uint64(0xFFFFFFFF00000000)) | at.astype(np.uint64), width)
    low = (low & np.uint64(0xFFFFFFFF)).astype(np.int64)
    size = np.maximum(np.diff(offsets) - length + 1, 0)
    start = np.repeat(offsets[:-1], size) + np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
    row = np.repeat(np.arange(len(size)), size)
    mine = low[start]
    head = np.flatnonzero(np.concatenate([[True], (mine[1:] != mine[:-1]) | (row[1:] != row[:-1])])) if len(mine) else none
    last = np.append(head[1:], len(mine)) - 1
    return g[mine[head]], row[head], start[head], start[last], roll


def _count(batches, length: int, gram: int):
    """(fp, blk, th, many, n): anchors of a run of rows, one row per anchor and block: the hash of a text that holds it,
    whether another text does or the same one twice, and how often it occurs."""
    for b in batches:
        data, off = tb.raw(b.column(2))
        blk, th = (b.column(k).to_numpy(zero_copy_only=False) for k in (0, 1))
        for i, j in tb.runs_of_rows(off, 1 << 21):
            g, row, _, _, _ = anchors(data[off[i] : off[j]], off[i : j + 1] - off[i], length, gram)
            if not len(g):
                continue
            row = row + i
            order = np.lexsort((row, blk[row], g))
            g, row = g[order], row[order]
            k, t = blk[row], th[row]
            same = (g[1:] == g[:-1]) & (k[1:] == k[:-1])
            head = np.flatnonzero(np.concatenate([[True], ~same]))
            other = np.concatenate([[False], same & ((row[1:] == row[:-1]) | (t[1:] != t[:-1]))])
            yield pa.RecordBatch.from_arrays(
                [pa.array(g[head].view(np.int64)), pa.array(k[head]), pa.array(t[head]), pa.array(np.logical_or.reduceat(other, head)), pa.array(np.diff(np.append(head, len(g))).astype(np.int32))],
                names=["fp", "blk", "th", "many", "n"],
            )


def _merge(doc: np.ndarray, s: np.ndarray, e: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Maximal runs of spans per document number (overlapping or touching)."""
    if not len(doc):
        return doc, s, e
    order = np.lexsort((s, doc))
    doc, s, e = doc[order].astype(np.int64), s[order], e[order]
    shift = doc * (int(e.max()) + 2)
    reach = np.maximum.accumulate(e + shift)
    head = np.flatnonzero(np.concatenate([[True], s[1:] + shift[1:] > reach[:-1]]))
    return doc[head], s[head], np.maximum.reduceat(e, head)


def _texts_in_order(table: pa.Table):
    """Sorted rows of a block: ids, text hashes, bytes, offsets; repeated rows once."""
    d = table.column("d").combine_chunks().fill_null(_MIN).to_numpy(zero_copy_only=False)
    th = table.column("th").to_numpy()
    order = np.lexsort((th, d))
    if len(order):
        keep = np.concatenate([[True], (d[order][1:] != d[order][:-1]) | (th[order][1:] != th[order][:-1])])
        order = order[keep]
    text = table.column("t").cast(pa.large_string()).combine_chunks().take(pa.array(order))
    return d[order], th[order], text


def _rows(kind, fp, cx, d, th, s, e, ctx):
    n = len(d)
    fill = lambda x: pa.array(np.full(n, x, np.int64) if np.isscalar(x) else x.astype(np.int64))
    return pa.table([pa.array(np.full(n, kind, np.int32)), fill(fp), fill(cx), fill(d), fill(th), fill(s), fill(e), ctx if ctx is not None else pa.nulls(n, pa.binary())], names=["kind", "fp", "cx", "d", "th", "s", "e", "ctx"])


def _cut(data: np.ndarray, begin: np.ndarray, end: np.ndarray) -> pa.Array:
    size = end - begin
    off = np.concatenate([[0], np.cumsum(size)])
    take = np.repeat(begin - off[:-1], size) + np.arange(off[-1])
    return pa.Array.from_buffers(pa.binary(), len(begin), [None, pa.py_buffer(off.astype(np.int32)), pa.py_buffer(np.ascontiguousarray(data[take]))])


def _contexts(texts: pa.Table, wanted: pa.Table, length: int, gram: int) -> pa.Table:
    """Step 2 for one block: contexts to compare (kind 0) and spans already known as covered (kind 1)."""
    out = []
    fps = wanted.column("fp").to_numpy().view(np.uint64)
    hot_of = wanted.column("hot").to_numpy(zero_copy_only=False)
    order = np.argsort(fps)
    fps, hot_of = fps[order], hot_of[order].astype(bool)
    d, th, column = _texts_in_order(texts)
    data, off = tb.raw(column)
    seen = np.zeros(0, np.uint64)
    done: list = []
    for i, j in tb.runs_of_rows(off, 1 << 21):
        part, o = data[off[i] : off[j]], off[i : j + 1] - off[i]
        g, row, begin, last, roll = anchors(part, o, length, gram)
        if not len(g) or not len(fps):
            continue
        k = np.searchsorted(fps, g)
        k[k == len(fps)] = 0
        known = fps[k] == g
        g, row, hot, begin, end = g[known], row[known], hot_of[k[known]], begin[known], last[known] + length
        if hot.any():
            m = np.maximum(0, end[hot] - begin[hot] - length + 1)
            wb = np.repeat(begin[hot], m) + np.arange(m.sum()) - np.repeat(np.cumsum(m) - m, m)
            route = tb.mix64(np.repeat(g[hot], m) ^ roll.of(wb, wb + gram) ^ (roll.of(wb + length - gram, wb + length) << np.uint64(1)))
            begin, end = np.concatenate([begin[~hot], wb]), np.concatenate([end[~hot], wb + length])
            g, row = np.concatenate([g[~hot], route]), np.concatenate([row[~hot], np.repeat(row[hot], m)])
        cx = roll.of(begin, end)
        key = tb.mix64(cx ^ tb.mix64(g))
        order = np.lexsort((begin, key))
        key_o = key[order]
        head = np.concatenate([[True], key_o[1:] != key_o[:-1]]) if len(key_o) else np.zeros(0, bool)
        if len(seen) and len(key_o):
            q = np.searchsorted(seen, key_o)
            q[q == len(seen)] = 0
            head &= seen[q] != key_o
        first, later = order[head], order[~head]
        seen = np.union1d(seen, key[first])
        done.append(_merge(row[later] + i, begin[later] - o[row[later]], end[later] - o[row[later]]))
        first.sort()
        out.append(_rows(0, g[first].view(np.int64), cx[first].view(np.int64), d[i + row[first]], th[i + row[first]], begin[first] - o[row[first]], end[first] - o[row[first]], _cut(part, begin[first], end[first])))
    for row, s, e in done:
        out.append(_rows(1, tb.mix64(d[row].view(np.uint64)).view(np.int64), 0, d[row], th[row], s, e, None))
    return pa.concat_tables(out) if out else _rows(0, *[np.zeros(0, np.int64)] * 6, None)


def suffix_order(data: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """(suffixes in order of their first ``length`` bytes, rank of each); equal prefixes share a rank. Bytes are
    given as 1..256, anything past the end counts as 0."""
    n = len(data)
    padded = np.concatenate([data, np.zeros(length + 8, np.uint16)]).astype(np.uint64)
    key = padded[:n]
    for k in range(1, 7):
        key = key * np.uint64(257) + padded[k : n + k]
    width = 7
    while True:
        order = np.argsort(key)
        o = key[order]
        rank = np.empty(n + length, np.int64)
        rank[n:] = 0
        rank[order] = np.cumsum(np.concatenate([[1], (o[1:] != o[:-1]).astype(np.int64)])) if n else rank[:0]
        if width >= length:
            return order, rank[:n]
        step = min(width, length - width)
        key = rank[:n] * np.int64(n + 1) + rank[step : n + step]
        width += step


def earlier_match(order: np.ndarray, rank: np.ndarray, place: np.ndarray) -> np.ndarray:
    """Which suffixes have a longest previous factor that spans the whole ranked prefix: their previous or next
    smaller place in suffix order has the same rank. Smaller neighbours are found by pointer jumping."""
    p, r = place[order], rank[order]
    n = len(p)
    out = np.zeros(n, bool)
    for way in (1, -1):
        q = p[::way]
        ptr = np.arange(n) - 1
        todo = np.flatnonzero(ptr >= 0)
        while len(todo):
            todo = todo[(ptr[todo] >= 0)]
            todo = todo[q[ptr[todo]] >= q[todo]]
            ptr[todo] = ptr[ptr[todo]]
        rr = r[::way]
        hit = (ptr >= 0) & (rr[np.maximum(ptr, 0)] == rr)
        out |= hit[::way]
    result = np.zeros(n, bool)
    result[order] = out
    return result


def _resolve(t: pa.Table, length: int) -> pa.Table:
    """Step 3 for whole anchors: the spans (d, th, s, e) with earlier matches."""
    kind = t.column("kind").to_numpy()
    col = {c: t.column(c).to_numpy() for c in ("fp", "cx", "d", "th", "s", "e")}
    pair = np.lexsort((col["th"], col["d"]))
    step = np.concatenate([[0], (np.diff(col["d"][pair]) != 0) | (np.diff(col["th"][pair]) != 0)]).astype(np.int64)
    doc = np.empty(len(pair), np.int64)
    doc[pair] = np.cumsum(step)
    spans = [np.stack([doc, col["s"], col["e"]])[:, kind == 1]]
    c = np.flatnonzero(kind == 0)
    if len(c):
        c = c[np.lexsort((col["s"][c], doc[c], col["cx"][c], col["fp"][c]))]
        fp, cx = col["fp"][c], col["cx"][c]
        head = np.concatenate([[True], (fp[1:] != fp[:-1]) | (cx[1:] != cx[:-1])])
        later = c[~head]
        spans.append(np.stack([doc[later], col["s"][later], col["e"][later]]))
        c = c[head]
        fp = col["fp"][c]
        same = fp[1:] == fp[:-1]
        crowd = np.concatenate([[False], same]) | np.concatenate([same, [False]])
        c = c[crowd | (col["e"][c] - col["s"][c] > length)]  # a long context may repeat within itself
        if len(c):
            data, off = tb.raw(t.column("ctx").combine_chunks().take(pa.array(c)))
            size = np.diff(off)
            ends = off[1:] + np.arange(len(c))
            text = np.zeros(len(data) + len(c), np.uint16)
            body = np.ones(len(text), bool)
            body[ends] = False
            text[body] = data.astype(np.uint16) + 1
            which = np.repeat(np.arange(len(c)), size + 1)
            inner = np.arange(len(text)) - (off[:-1] + np.arange(len(c)))[which]
            order, rank = suffix_order(text, length)
            place = doc[c][which] * (1 << 40) + col["s"][c][which] + inner
            whole = inner + length <= size[which]
            order = order[whole[order]]
            ok = np.zeros(len(text), bool)
            picked = np.flatnonzero(whole)
            back = np.full(len(text), -1)
            back[picked] = np.arange(len(picked))
            ok[picked] = earlier_match(back[order], rank[picked], place[picked])
            hit = np.flatnonzero(ok)
            s = col["s"][c][which[hit]] + inner[hit]
            spans.append(np.stack([doc[c][which[hit]], s, s + length]))
    allspans = np.concatenate(spans, axis=1)
    k, s, e = _merge(*allspans)
    some = np.zeros(int(doc.max()) + 1 if len(doc) else 0, np.int64)
    some[doc] = np.arange(len(doc))
    return pa.table([pa.array(col["d"][some[k]]), pa.array(col["th"][some[k]]), pa.array(s.astype(np.int64)), pa.array(e.astype(np.int64))], names=["d", "th", "s", "e"])


def _by_anchor(batches, length: int, budget: int = 2 << 20):
    """Feeds whole anchors (rows arrive sorted by fp) to ``_resolve`` in portions of bounded size."""
    held: list[pa.RecordBatch] = []
    size = 0
    for b in batches:
        held.append(b)
        size += b.nbytes
        if size < budget:
            continue
        t = pa.Table.from_batches(held)
        fp = t.column("fp").to_numpy()
        last = int(np.searchsorted(fp, fp[-1]))
        if last:
            yield from _resolve(t.slice(0, last), length).to_batches()
            t = t.slice(last).combine_chunks()
        held, size = t.to_batches(), 0 if t.nbytes < budget else t.nbytes // 2
    if held:
        t = pa.Table.from_batches(held)
        if t.num_rows:
            yield from _resolve(t, length).to_batches()


def _finish(texts: pa.Table, marks: pa.Table) -> pa.Table:
    """Step 4 for one block: what is left of each row."""
    d = texts.column("d").combine_chunks()
    dn, th = d.fill_null(_MIN).to_numpy(zero_copy_only=False), texts.column("th").to_numpy()
    data, off = tb.raw(texts.column("t").cast(pa.large_string()).combine_chunks())
    spans: dict = {}
    for a, b, s, e in zip(*(marks.column(c).to_pylist() for c in ("d", "th", "s", "e"))):
        spans.setdefault((_MIN if a is None else a, b), []).append((s, e))
    kept, removed, runs, starts, stops = [], [], [], [], []
    for i in range(len(dn)):
        raw = data[off[i] : off[i + 1]]
        mine = spans.get((int(dn[i]), int(th[i])))
        if not mine:
            kept.append(raw.tobytes())
            removed.append(0)
            starts.append([])
            stops.append([])
            continue
        x = np.array(mine, np.int64)
        _, s, e = _merge(np.zeros(len(x), np.int64), x[:, 0], np.minimum(x[:, 1], len(raw)))
        mask = np.zeros(len(raw) + 1, np.int64)
        mask[s] += 1
        mask[e] -= 1
        kept.append(raw[np.cumsum(mask[:-1]) == 0].tobytes())
        removed.append(int((e - s).sum()))
        starts.append(s.tolist())
        stops.append(e.tolist())
    return pa.table([d, pa.array(np.diff(off)), pa.array(removed, pa.int64()), pa.array(starts, pa.list_(pa.int64())), pa.array(stops, pa.list_(pa.int64())), pa.array(kept, pa.binary())], names=["d", "n_bytes", "n_removed", "starts", "stops", "kept"])


def remove_repeats(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", length: int = LENGTH, gram: int = GRAM, block_bytes: int = BLOCK_BYTES, hot: int = HOT) -> DataFrame:
    """(d, n_bytes, n_removed, starts, stops, kept) for every row: the maximal removed byte runs, and the rest.

    Null text is empty. A null id comes before all others. Rows that repeat an id and its text are one document
    and come out alike; different texts under one id order by their hash. Empty tables give empty results.
    """
    spark = docs.sparkSession
    t = F.coalesce(F.col(text), F.lit(""))
    total = docs.agg(F.sum(F.octet_length(t))).first()[0] or 0
    blocks = max(32, -(-int(total) // block_bytes))
    block = lambda c: F.pmod(F.xxhash64(c), F.lit(blocks)).cast("int")
    id_ = F.col(doc_id).cast("long")
    rows = docs.select(block(id_).alias("blk"), id_.alias("d"), F.xxhash64(t).alias("th"), t.alias("t"))

    whole = docs.select(id_.alias("d"), F.xxhash64(t).alias("th"), F.xxhash64(F.lit(29), t).alias("t2"), F.octet_length(t).cast("long").alias("n")).where(F.col("n") >= length)
    firsts = settle(whole.groupBy("th", "t2", "n").agg(F.min(F.struct("d")).alias("f"), F.max(F.struct("d")).alias("l")).where("f <> l").select(F.col("th").alias("fh"), F.col("t2").alias("f2"), F.col("n").alias("fn"), "f"))
    copies = whole.join(firsts.hint("merge"), F.expr("th = fh and t2 = f2 and n = fn")).where(F.struct("d") > F.col("f"))
    copies = copies.select("d", "th", F.lit(0).cast("long").alias("s"), F.col("n").alias("e"))

    counted = arrow_map(rows.select("blk", "th", "t"), lambda it: _count(it, length, gram), "fp long, blk int, th long, many boolean, n int")
    same = W.partitionBy("fp")
    judged = counted.select("fp", "blk", F.min("th").over(same).alias("lo"), F.max("th").over(same).alias("hi"), F.max("many").over(same).alias("many"), F.sum("n").over(same).alias("n"))
    wanted = judged.where("lo <> hi or many").select("blk", "fp", (F.col("n") > hot).alias("hot"))

    def contexts(texts: pa.Table, fps: pa.Table) -> pa.Table:
        return _contexts(texts, fps, length, gram)

    cut = rows.groupBy("blk").cogroup(wanted.groupBy("blk")).applyInArrow(contexts, _SCHEMA)
    met = cut.repartition(spark_partitions(spark), "fp").sortWithinPartitions("fp")
    marks = arrow_map(met, lambda it: _by_anchor(it, length), "d long, th long, s long, e long")
    marks = marks.select(F.when(F.col("d") != _MIN, F.col("d")).alias("d"), "th", "s", "e").union(copies)
    marks = marks.withColumn("blk", block(F.col("d")))
    done = rows.groupBy("blk").cogroup(marks.groupBy("blk")).applyInArrow(lambda a, b: _finish(a, b), "d long, n_bytes long, n_removed long, starts array<long>, stops array<long>, kept binary")
    return done.withColumnRenamed("d", doc_id)


def spark_partitions(spark) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def substring_query(docs: DataFrame) -> DataFrame:
    """The contract's columns for every row; nulls, repeats and empty tables as in ``remove_repeats``."""
    out = remove_repeats(docs.select("doc_id", "text"))
    return out.select("doc_id", "n_bytes", "n_removed", F.size("starts").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))
