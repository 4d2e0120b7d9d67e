"""Mixing sources to target weights by proportionate-fair scheduling.

In the ideal course every source with rows left gets slots at the rate of its weight, divided by the weights
of all sources with rows left. A block is released in the slot in which the ideal course begins it and due at
the end of the one in which the course ends it. The ideal course itself fits these windows, so taking
the released block of earliest deadline in every slot misses none, and every source stays within one block of
its ideal share at every moment, from the first slot to the last. Times are exact rationals of the weights.

When a source runs out its weight is shared among the others and a new phase starts; no row is dropped or
repeated and no slot stays empty. The driver holds the sources and takes one heap step per block, so ``block_docs``
has to grow with very large tables (65,536 documents a block make 1.5 million steps of 10**11 documents).
"""

from __future__ import annotations

import heapq
from bisect import bisect_left, bisect_right
from fractions import Fraction
from math import lcm

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import fresh

BLOCK_DOCS = 16
#: Sources and blocks up to which the schedule is broadcast; a larger one meets the rows by a merge join.
MAX_SOURCES = 512
BROADCAST_BLOCKS = 1 << 20
#: Blocks of a source in one row of the schedule.
CHUNK = 1024
#: Rows per rank bucket, and the letters of md5 that name a bucket.
BUCKET_ROWS = 20_000


def schedule(blocks: dict, weights: dict) -> tuple[dict, list]:
    """(slots of each source's blocks in order, slots from which phases count) for any number of sources.

    Sources of weight 0 come after all others, in equal shares."""
    if any(weights[k] < 0 for k in blocks):
        raise ValueError("weights must not be negative")
    names = sorted(k for k, n in blocks.items() if n > 0 and weights[k] > 0)
    last = [k for k, n in blocks.items() if n > 0 and weights[k] == 0]
    exact = [Fraction(weights[k]) for k in names]
    scale = lcm(*(x.denominator for x in exact))
    w, n = [int(x * scale) for x in exact], [blocks[k] for k in names]
    # In phase p the slot reached is done[p] + rate[p] * v, where v, the blocks per unit of weight, runs to ends[p].
    ends, done, rate = [], [0], [sum(w)]
    for v, i in sorted((Fraction(n[i], w[i]), i) for i in range(len(names))):
        if not ends or v > ends[-1]:
            ends.append(v)
            done.append(done[-1])
            rate.append(rate[-1])
        done[-1] += n[i]
        rate[-1] -= w[i]
    total, phase = sum(n), [0] * len(names)
    slots: dict = {k: [] for k in names}
    waiting, ready = [(0, i) for i in range(len(names))], []
    for slot in range(total):
        while waiting and waiting[0][0] <= slot:
            i = heapq.heappop(waiting)[1]
            j, p = len(slots[names[i]]) + 1, phase[i]
            if j * ends[p].denominator > ends[p].numerator * w[i]:
                p = phase[i] = bisect_left(ends, Fraction(j, w[i]), p)
            whole, rest = divmod(rate[p] * j, w[i])
            heapq.heappush(ready, (done[p] + whole + (rest > 0), i, done[p] + whole))
        if not ready:
            raise AssertionError("the ideal course leaves no slot idle")
        due, i, release = heapq.heappop(ready)
        if due < slot + 1:
            raise AssertionError("deadline missed")
        slots[names[i]].append(slot)
        if len(slots[names[i]]) < n[i]:
            heapq.heappush(waiting, (max(slot + 1, release), i))
    starts = [done[p] + -(-rate[p] * v.numerator // (v.denominator)) for p, v in enumerate(ends)]
    if last:
        more, later = schedule({k: blocks[k] for k in last}, dict.fromkeys(last, 1))
        slots |= {k: [total + t for t in x] for k, x in more.items()}
        starts += [total + t for t in later]
    return slots, starts


def source_key(source: str):
    """A source as text, null being a value of its own."""
    return F.coalesce(F.concat(F.lit("s:"), F.col(source).cast("string")), F.lit("n:"))


def ranked(docs: DataFrame, n_rows: int, doc_id: str, key, bucket_rows: int = BUCKET_ROWS) -> DataFrame:
    """Adds ``mix_key`` and ``mix_rank`` (0-based place within the key, in the order of md5 of the id). Ranks are counted
    per md5 bucket and shifted by the buckets before, so a source of any size is spread over tasks."""
    f = fresh(docs, "_mix_")
    letters = 1
    while 16**letters * bucket_rows < n_rows:
        letters += 1
    keyed = docs.withColumns({"mix_key": key, f"{f}md5": F.md5(F.coalesce(F.col(doc_id).cast("string"), F.lit("")))}).withColumn(f"{f}bucket", F.substring(f"{f}md5", 1, letters))
    count = keyed.groupBy("mix_key", f"{f}bucket").agg(F.count("*").alias("n"))
    before = F.sum("n").over(W.partitionBy("mix_key").orderBy(f"{f}bucket").rowsBetween(W.unboundedPreceding, 0)) - F.col("n")
    shift = count.select(F.col("mix_key").alias(f"{f}k"), F.col(f"{f}bucket").alias(f"{f}b"), before.alias(f"{f}shift"))
    inside = F.row_number().over(W.partitionBy("mix_key", f"{f}bucket").orderBy(f"{f}md5", doc_id))
    out = keyed.withColumn(f"{f}in", inside).join(shift.hint("merge"), F.expr(f"mix_key = {f}k and {f}bucket = {f}b"))
    out = out.withColumn("mix_rank", (F.col(f"{f}shift") + F.col(f"{f}in") - 1).cast("long"))
    return out.drop(*[f + x for x in ("md5", "bucket", "k", "b", "shift", "in")])


def mix(docs: DataFrame, weights: dict | None = None, doc_id: str = "doc_id", source: str = "source", block_docs: int = BLOCK_DOCS, temperature: float = 0.5) -> DataFrame:
    """Every row of ``docs`` with mix_phase, mix_block, mix_slot and mix_order (slot, then place in the block; columns so
    named are replaced). ``weights``
    maps sources to targets; without it the target is rows ** temperature, and sources not named in it get what the
    smallest named one has. Null sources form one source of their own. Every source, however many there are, is
    scheduled by its own exact target;
    An empty table gives an empty result; repeated rows are placed one by one; ties in md5 go by id.
    """
    spark = docs.sparkSession
    given = {f"s:{k}" if k is not None else "n:": Fraction(w) for k, w in (weights or {}).items()}
    floor = min(given.values(), default=None)
    counts = {r["k"]: r["n"] for r in docs.groupBy(source_key(source).alias("k")).agg(F.count("*").alias("n")).collect()}
    target = {k: given.get(k, floor) if given else Fraction(float(n) ** temperature) for k, n in counts.items()}
    slots, starts = schedule({k: -(-n // block_docs) for k, n in counts.items()}, target)
    rows = []
    for k, at in slots.items():
        for c, lo in enumerate(range(0, len(at), CHUNK)):
            part = at[lo : lo + CHUNK]
            rows.append((k, c, part, [bisect_right(starts, t) for t in part]))
    f = fresh(docs, "_mix_")
    table = spark.createDataFrame(rows or [("", 0, [0], [0])], f"{f}key string, {f}part long, {f}slots array<long>, {f}phases array<int>")
    small = len(counts) <= MAX_SOURCES and sum(len(x) for x in slots.values()) <= BROADCAST_BLOCKS
    table = F.broadcast(table) if small else table.hint("merge")
    held = {c: f"{f}own_{c}" for c in docs.columns if c.lower() in ("mix_key", "mix_rank")}
    clean = docs.drop("mix_phase", "mix_block", "mix_slot", "mix_order").withColumnsRenamed(held)
    placed = ranked(clean, sum(counts.values()), doc_id, source_key(source)).withColumn("mix_block", F.floor(F.col("mix_rank") / block_docs).cast("long"))
    joined = placed.join(table, F.expr(f"mix_key = {f}key and mix_block div {CHUNK} = {f}part"))
    place = F.expr(f"cast(mix_block % {CHUNK} + 1 as int)")
    out = joined.withColumns({"mix_phase": F.element_at(f"{f}phases", place), "mix_slot": F.element_at(f"{f}slots", place)})
    out = out.withColumn("mix_order", (F.col("mix_slot") * block_docs + F.col("mix_rank") % block_docs).cast("long"))
    out = out.drop("mix_key", "mix_rank", *[f + x for x in ("key", "part", "slots", "phases")])
    return out.withColumnsRenamed({b: a for a, b in held.items()})


def mixing_query(docs: DataFrame) -> DataFrame:
    """Every id with its place in the schedule of its source; nulls, repeated rows and empty tables as in ``mix``."""
    return mix(docs.select("doc_id", "source")).select("doc_id", "source", "mix_phase", "mix_block", "mix_slot", "mix_order")
