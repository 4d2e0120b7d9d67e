"""Benchmark decontamination with an FM-index per shard of the corpus.

A shard is one Arrow batch of documents. Only words that can lie inside a benchmark window enter its index:
maximal runs of benchmark words joined by benchmark word pairs, of at least the shortest window's length.
The index is a Burrows-Wheeler transform over word symbols held in a wavelet matrix, with suffix positions
sampled at every eighth word and at the head of each run. All windows search backwards at once; occurrences are
located by walking to the nearest sample, and their spans merge per document.

The benchmark is held as its text in symbols with the places where distinct windows start; windows are read off it while
searching. A part of ``PASS_BYTES`` takes some 25 bytes a word beside its words' hashes, about 70 MB for prose, and is broadcast.
A larger benchmark goes in several passes, each of which carries the rows of the one before, so results never
depend on the number of passes.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fadedhh.shipping import arrow_map

from . import textbytes as tb
from .common import settle

WINDOW = 13
#: Bytes of benchmark text held by one pass.
PASS_BYTES = 16 << 20


class WordIndex:
    """FM-index of runs of symbols >= 1, each run closed by the separator 0."""

    SAMPLE = 8

    def __init__(self, text: np.ndarray, symbols: int):
        n = len(text)
        self.n = n
        stop = text == 0
        rank = text.astype(np.int64) + stop.sum()
        rank[stop] = np.arange(stop.sum())
        step = 1
        order = np.argsort(rank, kind="stable")
        while True:
            in_order = rank[order]
            fresh = np.concatenate([[0], (in_order[1:] != in_order[:-1]).astype(np.int64)])
            dense = np.empty(n, np.int64)
            dense[order] = np.cumsum(fresh)
            if n == 0 or dense[order[-1]] == n - 1:
                break
            after = np.zeros(n, np.int64)
            after[: max(0, n - step)] = dense[step:] + 1
            rank = dense * (n + 1) + after
            order = np.argsort(rank, kind="stable")
            step *= 2
        self.levels = max(1, int(symbols).bit_length())
        before = np.where(order > 0, text[order - 1], 0)
        self.first = np.concatenate([[0], np.cumsum(np.bincount(text, minlength=symbols + 1))])
        self.ones, self.zeros = [], []
        seq = before
        for level in range(self.levels - 1, -1, -1):
            bit = (seq >> level) & 1
            self.ones.append(np.concatenate([[0], np.cumsum(bit)]))
            self.zeros.append(n - int(bit.sum()))
            seq = np.concatenate([seq[bit == 0], seq[bit == 1]])
        head = np.ones(n, bool)
        head[1:] = stop[:-1]
        sampled = head | (np.arange(n) % self.SAMPLE == 0)
        self.marked = sampled[order]
        self.mark_rank = np.concatenate([[0], np.cumsum(self.marked)])
        self.samples = order[self.marked]

    def _down(self, symbol: np.ndarray, *ends: np.ndarray) -> list[np.ndarray]:
        """Ranks of each symbol before each end."""
        at = [np.zeros(len(symbol), np.int64), *ends]
        for level, (ones, zeros) in enumerate(zip(self.ones, self.zeros)):
            bit = (symbol >> (self.levels - 1 - level)) & 1
            at = [np.where(bit == 1, zeros + ones[x], x - ones[x]) for x in at]
        return [x - at[0] for x in at[1:]]

    def _symbol(self, row: np.ndarray) -> np.ndarray:
        out = np.zeros(len(row), np.int64)
        x = row
        for ones, zeros in zip(self.ones, self.zeros):
            bit = ones[x + 1] - ones[x]
            out = (out << 1) | bit
            x = np.where(bit == 1, zeros + ones[x], x - ones[x])
        return out

    def ranges(self, text: np.ndarray, start: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(pattern numbers, low rows, high rows) of the patterns text[start : start + width] that occur."""
        occurs = np.diff(self.first) > 0
        who = np.flatnonzero(occurs[text[start + (width - 1)]])
        lo, hi = np.zeros(len(who), np.int64), np.full(len(who), self.n, np.int64)
        for j in range(width - 1, -1, -1):
            c = text[start[who] + j].astype(np.int64)
            a, b = self._down(c, lo, hi)
            lo, hi = self.first[c] + a, self.first[c] + b
            live = hi > lo
            who, lo, hi = who[live], lo[live], hi[live]
        return who, lo, hi

    def locate(self, row: np.ndarray) -> np.ndarray:
        """Text positions of suffix rows."""
        out = np.empty(len(row), np.int64)
        which, steps = np.arange(len(row)), 0
        while len(row):
            done = self.marked[row]
            out[which[done]] = self.samples[self.mark_rank[row[done]]] + steps
            which, row = which[~done], row[~done]
            c = self._symbol(row)
            row = self.first[c] + self._down(c, row)[0]
            steps += 1
        return out


class Windows:
    """A benchmark part: its text as symbols, and per window length where each distinct window starts and which items hold it."""

    def __init__(self, ids: pa.Array, texts: pa.Array, window: int):
        h, count = tb.words(*tb.raw(texts), tb.ALNUM)
        self.items = sorted(set(ids.to_pylist()))
        place = {x: i for i, x in enumerate(self.items)}
        item = np.array([place[x] for x in ids.to_pylist()], np.int32)
        self.vocabulary = np.unique(h)
        self.text = (np.searchsorted(self.vocabulary, h) + 1).astype(np.int32)
        end = np.cumsum(count)
        width = np.minimum(count, window)
        inner = np.ones(len(h), bool)
        inner[end[count > 0] - 1] = False
        at = np.flatnonzero(inner)
        self.pairs = np.unique(self.text[at].astype(np.uint64) << np.uint64(32) | self.text[at + 1].astype(np.uint64)) if len(at) else np.zeros(0, np.uint64)
        self.shortest = int(width[width > 0].min()) if (width > 0).any() else 0
        self.by_length = []
        for w in np.unique(width[width > 0]).tolist():
            rows = np.flatnonzero(width == w)
            m = count[rows] - w + 1
            start = np.repeat(end[rows] - count[rows] - np.cumsum(m) + m, m) + np.arange(m.sum())
            key = np.zeros(len(start), np.uint64)
            for k, p in enumerate(tb.powers(w + 1)[1:]):
                key += h[start + k] * p
            _, one, back = np.unique(key, return_index=True, return_inverse=True)
            owner = np.unique(back.astype(np.uint64) << np.uint64(32) | np.repeat(item[rows], m).astype(np.uint64))
            bounds = np.searchsorted(owner, np.arange(len(one) + 1, dtype=np.uint64) << np.uint64(32))
            self.by_length.append((w, start[one].astype(np.int32), owner.astype(np.int32), bounds.astype(np.int32)))
        self.sieve = np.zeros(1 << 20, bool)
        self.sieve[(self.vocabulary >> np.uint64(44)).astype(np.int64)] = True

    def runs(self, h: np.ndarray, count: np.ndarray):
        """(symbols with separators, word index of each, row of each) of the words that can be in a window."""
        n = len(h)
        maybe = np.flatnonzero(self.sieve[(h >> np.uint64(44)).astype(np.int64)])
        near = np.searchsorted(self.vocabulary, h[maybe])
        near[near == len(self.vocabulary)] = 0
        real = self.vocabulary[near] == h[maybe] if len(self.vocabulary) else np.zeros(0, bool)
        at, symbol = maybe[real], near[real] + 1
        if not len(at):
            return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
        ends = np.cumsum(count)
        row = np.searchsorted(ends, at, side="right")
        joined = (at[1:] == at[:-1] + 1) & (row[1:] == row[:-1])
        key = symbol[:-1].astype(np.uint64) << np.uint64(32) | symbol[1:].astype(np.uint64)
        check = np.flatnonzero(joined)
        if len(self.pairs):
            k = np.searchsorted(self.pairs, key[check])
            k[k == len(self.pairs)] = 0
            joined[check] = self.pairs[k] == key[check]
        else:
            joined[:] = False
        begin = np.flatnonzero(np.concatenate([[True], ~joined]))
        size = np.diff(np.append(begin, len(at)))
        begin, size = begin[size >= self.shortest], size[size >= self.shortest]
        if not len(begin):
            return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
        total = size + 1
        off = np.arange(total.sum()) - np.repeat(np.cumsum(total) - total, total)
        pick = np.minimum(np.repeat(begin, total) + off, len(at) - 1)
        is_stop = off == np.repeat(size, total)
        return np.where(is_stop, 0, symbol[pick]), np.where(is_stop, -1, at[pick]), row[pick]


def _scan(column: pa.Array, bench: Windows):
    """Per row: (n_words, hit word spans, item numbers) of one shard."""
    data, offsets = tb.raw(column)
    counts, texts, places, rows, base = [], [], [], [], 0
    for i, j in tb.runs_of_rows(offsets, 1 << 21):
        h, count = tb.words(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], tb.ALNUM)
        counts.append(count)
        if bench.shortest:
            t, at, row = bench.runs(h, count)
            start = np.concatenate([[0], np.cumsum(count)])
            texts.append(t)
            places.append(np.where(at >= 0, at - start[row], -1))
            rows.append(row + i)
    counts = np.concatenate([np.zeros(0, np.int64), *counts])
    none = np.zeros(0, np.int64)
    text, place, row = (np.concatenate([none, *x]) for x in (texts, places, rows))
    hit_row, hit_item = [none], [none]
    cover = np.zeros(len(text) + 1, np.int64)
    if len(text):
        index = WordIndex(text, len(bench.vocabulary))
        for width, start, owners, bounds in bench.by_length:
            who, lo, hi = index.ranges(bench.text, start, width)
            if not len(who):
                continue
            m = hi - lo
            suffix = np.repeat(lo, m) + np.arange(m.sum()) - np.repeat(np.cumsum(m) - m, m)
            pos, of = index.locate(suffix), np.repeat(who, m)
            np.add.at(cover, pos, 1)
            np.add.at(cover, pos + width, -1)
            key = np.unique(of * np.int64(len(counts) + 1) + row[pos])
            of, doc = key // (len(counts) + 1), key % (len(counts) + 1)
            k = bounds[of + 1] - bounds[of]
            hit_row.append(np.repeat(doc, k))
            hit_item.append(owners[np.repeat(bounds[of], k) + np.arange(k.sum()) - np.repeat(np.cumsum(k) - k, k)])
    hit = np.cumsum(cover[:-1]) > 0
    open_ = np.flatnonzero(hit & ~np.concatenate([[False], hit[:-1]]))
    shut = np.flatnonzero(hit & ~np.concatenate([hit[1:], [False]]))
    key = np.unique(np.concatenate(hit_row) * np.int64(len(bench.items) + 1) + np.concatenate(hit_item))
    return counts, row[open_], place[open_], place[shut], key // (len(bench.items) + 1), key % (len(bench.items) + 1)


def _bench_passes(benchmark: DataFrame, item_id: str, text: str, window: int, pass_bytes: int):
    """The benchmark in parts of bounded size; the last one is marked."""
    rows = benchmark.select(F.col(item_id).cast("string").alias("i"), F.coalesce(F.col(text), F.lit("")).alias("t")).where("i is not null")
    size = rows.agg(F.sum(F.octet_length("t") + 64)).first()[0] or 0
    passes = max(1, -(-int(size) // pass_bytes))
    for p in range(passes):
        got = (rows if passes == 1 else rows.where(F.pmod(F.xxhash64("i", "t"), F.lit(passes)) == p)).toArrow().combine_chunks()
        yield p == passes - 1, Windows(*(c.combine_chunks() if isinstance(c, pa.ChunkedArray) else c for c in got.columns), window)


def contamination(docs: DataFrame, benchmark: DataFrame, doc_id: str = "doc_id", text: str = "text", item_id: str = "item_id", window: int = WINDOW, pass_bytes: int = PASS_BYTES) -> DataFrame:
    """(doc_id, th, n_words, spans, items): words, merged hit spans (first and last word, 0-based) and the ids of
    items with an occurring window, sorted as strings. One row per row of ``docs``, whatever the number of passes.
    Null has no words; benchmark rows without id are ignored. Empty tables give empty results, an empty benchmark no spans."""
    out = docs.select(F.col(doc_id).alias("doc_id"), F.xxhash64(text).alias("th"), F.col(text).alias("t"))
    for k, (last, bench) in enumerate(_bench_passes(benchmark, item_id, "text", window, pass_bytes)):
        out = _one_pass(settle(out) if k else out, bench, last)
    return out


def _merged(spans: list, items: list, more: list, names: list) -> tuple[list, list]:
    """Union of two sorted lists of spans, and of two sorted lists of names."""
    out: list = []
    for x in sorted([(x["s"], x["e"]) for x in [*spans, *more]]):
        if out and x[0] <= out[-1]["e"] + 1:
            out[-1]["e"] = max(out[-1]["e"], x[1])
        else:
            out.append({"s": x[0], "e": x[1]})
    return out, sorted({*items, *names})


def _one_pass(frame: DataFrame, bench: Windows, last: bool) -> DataFrame:
    """Adds what one part of the benchmark finds to rows (doc_id, th, t) or to those of the pass before; the last leaves t out."""
    held = frame.sparkSession.sparkContext.broadcast(bench)
    names = ["doc_id", "th", "t", "n_words", "spans", "items"]
    frame = frame.select(*[c for c in names if c in frame.columns])

    def run(batches):
        bench = held.value
        for b in batches:
            counts, row, s, e, irow, item = _scan(b.column(2), bench)
            n = len(counts)
            at = np.searchsorted(row, np.arange(n + 1))
            iat = np.searchsorted(irow, np.arange(n + 1))
            spans = pa.ListArray.from_arrays(pa.array(at.astype(np.int32)), pa.StructArray.from_arrays([pa.array(s), pa.array(e)], names=["s", "e"]))
            found = pa.ListArray.from_arrays(pa.array(iat.astype(np.int32)), pa.array([bench.items[k] for k in item.tolist()], pa.string()))
            if b.num_columns > 3:
                both = [_merged(*x) for x in zip(b.column(4).to_pylist(), b.column(5).to_pylist(), spans.to_pylist(), found.to_pylist())]
                spans, found = pa.array([x[0] for x in both], spans.type), pa.array([x[1] for x in both], found.type)
            out = pa.RecordBatch.from_arrays([*b.columns[:3], pa.array(counts, pa.int64()), spans, found], names=names)
            yield out.select([c for c in names if c != "t"]) if last else out

    return arrow_map(frame, run, f"doc_id {dict(frame.dtypes)['doc_id']}, th long,{'' if last else ' t string,'} n_words long, spans array<struct<s:long,e:long>>, items array<string>")


def verdicts(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """Adds n_hit and contaminated (some hit, and at least a twentieth of the words) to the spans and items."""
    out = contamination(docs, benchmark, **options)
    out = out.withColumn("n_hit", F.aggregate("spans", F.lit(0).cast("long"), lambda a, x: a + x["e"] - x["s"] + 1))
    return out.withColumn("contaminated", (F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words")))


def decontam_query(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The contract's columns, one row per row of ``docs``; nulls and empty tables as in ``contamination``."""
    out = verdicts(docs.select("doc_id", "text"), benchmark)
    return out.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), "contaminated")


_WORDS = "regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+')"
ORACLE = f"""
WITH d AS (SELECT doc_id, {_WORDS} AS ws FROM documents),
b AS (SELECT item_id::VARCHAR AS item, {_WORDS} AS ws FROM benchmark WHERE item_id IS NOT NULL),
g AS (SELECT DISTINCT item, least(len(ws), {WINDOW}) AS w, unnest(list_transform(range(1, len(ws) - least(len(ws), {WINDOW}) + 2), lambda i: array_to_string(ws[i:i + least(len(ws), {WINDOW}) - 1], ' '))) AS s FROM b WHERE len(ws) > 0),
l AS (SELECT DISTINCT w FROM g),
p AS (SELECT doc_id, ws, w, unnest(range(1, len(ws) - w + 2)) AS i FROM d, l WHERE len(ws) >= w),
q AS (SELECT doc_id, i, w, array_to_string(ws[i:i + w - 1], ' ') AS s FROM p),
o AS (SELECT doc_id, i, q.w AS w, item FROM q JOIN g ON q.s = g.s AND q.w = g.w),
h AS (SELECT doc_id, count(DISTINCT i) AS n FROM (SELECT doc_id, unnest(range(i, i + w)) AS i FROM o) GROUP BY doc_id),
t AS (SELECT doc_id, count(DISTINCT item) AS n, list_sort(list(DISTINCT item)) AS items FROM o GROUP BY doc_id)
SELECT d.doc_id, len(ws)::BIGINT AS n_words, coalesce(h.n, 0)::BIGINT AS n_hit, coalesce(t.n, 0)::BIGINT AS n_items,
  sha256(coalesce(array_to_string(items, ','), '')) AS items_sha256, coalesce(h.n, 0) > 0 AND 20 * coalesce(h.n, 0) >= len(ws) AS contaminated
FROM d LEFT JOIN h ON h.doc_id = d.doc_id LEFT JOIN t ON t.doc_id = d.doc_id
"""
