"""Line deduplication: winnowing over line hashes, joined positions, matches extended both ways.

From every line that is not blank a window runs over as many lines as it takes to reach ``min_chars`` characters. The
smallest line hash in a window is its fingerprint (of equal ones the first), so two equal windows have equal
fingerprints at equal places: a run of ``min_chars`` characters that occurs twice always shares one.

1. Fingerprints that stand at one place only are done with, and so are their windows.
2. Places of the others are joined: every later copy of a window, found through its fingerprint and compared by the hash
   of its whole content, meets the first copy of it (smaller id, then earlier line).
3. Matches grow both ways while lines are equal. To the right, line by line, no farther than the end of the window
   that starts one line later: if all lines up to there are equal, that window is a later copy itself and carries on. To
   the left, over blank lines: a line before them that is equal too starts a window that lies in the match, which is
   likewise a later copy itself.
4. Matches merge into runs, and the runs go. The first copy stays.

Nothing is cut off: a window may have any number of lines, and a match any length. Only DataFrame functions; every
aggregation combines before its shuffle, and the joins are plain ones over settled tables, which Spark may split where a
passage is very common.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import fresh, settle

MIN_CHARS = 120


def _reach(part, min_chars: int):
    """(n, chars, p, low): size, end and fingerprint (hash, line) of the shortest head of ``part`` with min_chars characters, or of
    all of it.
    A line that is not blank has a character, so no more than min_chars lines are ever looked at."""
    start = F.struct(F.lit(0).alias("n"), F.lit(0).alias("chars"), F.lit(0).alias("p"), F.struct(F.lit((1 << 63) - 1).alias("h"), F.lit(0).alias("p")).alias("low"))
    grow = lambda acc, x: F.when(acc["chars"] >= min_chars, acc).otherwise(F.struct((acc["n"] + 1).alias("n"), (acc["chars"] + x["c"]).alias("chars"), x["p"].alias("p"), F.least(acc["low"], F.struct(x["h"], x["p"])).alias("low")))
    return F.aggregate(part, start, grow)


def _windows(docs: DataFrame, doc_id: str, text: str, min_chars: int) -> DataFrame:
    """(d, th, s, n, run, low, at, lead, tail): windows of n lines from line s (1-based), the hash of their whole content, their
    fingerprint and its line, the blank lines before them, and what follows them up to the end of the next window: (line hash, distance
    from s) of lines that are not blank, then hash 0 for the end of the text if that is nearer."""
    base = docs.select(F.col(doc_id).alias("d"), F.xxhash64(F.coalesce(F.col(text), F.lit(""))).alias("th"), F.split(F.coalesce(F.col(text), F.lit("")), "\n").alias("ls"))
    full = F.filter(F.transform("ls", lambda x, i: F.struct(F.xxhash64(x).alias("h"), F.length(x).alias("c"), (i + 1).alias("p"))), lambda x: x["c"] > 0)
    base = base.select("d", "th", full.alias("ls"), (F.size("ls") + 1).alias("z"))
    steps = sorted({min(8, min_chars), min_chars})

    def first_of(i, sizes):
        got = _reach(F.slice("ls", i + 1, sizes[0]), min_chars)
        return got if len(sizes) == 1 else F.transform(F.array(got), lambda r: F.when(r["chars"] >= min_chars, r).otherwise(first_of(i, sizes[1:])))[0]

    reach = base.withColumn("to", F.transform("ls", lambda x, i: first_of(i, steps)))

    def row(x, i):
        to = F.get("to", i)
        core = F.slice("ls", i + 1, to["n"])
        before = F.when(i > 0, F.get("ls", i - 1)["p"]).otherwise(0)
        later = F.get("to", i + 1)
        ends = later.isNull() | (later["chars"] < min_chars)  # the text ends before the next window does
        more = F.when(ends, F.size("ls") - i - to["n"]).otherwise(later["n"] + 1 - to["n"])
        follow = F.transform(F.slice("ls", i + 1 + to["n"], F.greatest(more, F.lit(0))), lambda y: F.struct(y["h"].alias("h"), (y["p"] - x["p"]).alias("o")))
        stop = F.filter(F.array(F.struct(F.lit(0).cast("long").alias("h"), (F.col("z") - x["p"]).alias("o"))), lambda _: ends)
        return F.struct(
            x["p"].alias("s"), (to["p"] - x["p"] + 1).alias("n"), F.xxhash64(F.transform(core, lambda y: F.struct(y["h"], y["p"] - x["p"]))).alias("run"), to["low"]["h"].alias("low"), to["low"]["p"].alias("at"),
            (x["p"] - before - 1).alias("lead"), F.concat(follow, stop).alias("tail"), to["chars"].alias("chars"),
        )

    rows = reach.select("d", "th", F.inline(F.filter(F.transform("ls", row), lambda r: r["chars"] >= min_chars)))
    return rows.drop("chars")


def matches(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", min_chars: int = MIN_CHARS) -> DataFrame:
    """(d, th, s, e): lines s to e of a text (id, hash of the text) equal the lines around the first copy of one of their windows."""
    windows = settle(_windows(docs, doc_id, text, min_chars))
    place = F.xxhash64("d", "th", "at")
    fingers = windows.groupBy("low").agg(F.min(place).alias("a"), F.max(place).alias("z"))
    shared = settle(fingers.where("a <> z").select(F.col("low").alias("shared")))
    found = settle(windows.join(shared.hint("merge"), F.col("low") == F.col("shared"), "left_semi"))
    start = F.struct("d", "th", F.col("s").cast("long").alias("p"))
    several = found.groupBy("run", "n").agg(F.min(start).alias("a"), F.max(start).alias("z")).where("a <> z")
    several = settle(several.select(F.col("run").alias("r"), F.col("n").alias("m"), F.col("a.d").alias("d0"), F.col("a.th").alias("th0"), F.col("a.p").cast("int").alias("s0")))
    origin = found.join(several.hint("merge"), F.expr("run = r and n = m and d <=> d0 and th = th0 and s = s0"))
    origin = settle(origin.groupBy("r", "m").agg(F.first("d0").alias("d0"), F.first("th0").alias("th0"), F.first("s0").alias("s0"), F.first("lead").alias("lead0"), F.first("tail").alias("tail0")))
    both = found.join(origin.hint("merge"), F.expr("run = r and n = m")).where(~F.expr("d <=> d0 and th = th0 and s = s0"))
    same = F.array_position(F.zip_with("tail", "tail0", lambda a, b: a.eqNullSafe(b)), F.lit(False)) - 1  # -1: all are equal
    own, other = F.get("tail", same.cast("int"))["o"], F.get("tail0", same.cast("int"))["o"]
    last = F.get("tail", F.size("tail") - 1)
    whole = F.when(F.size("tail") == 0, F.col("n") - 1).when(last["h"] == 0, last["o"] - 1).otherwise(last["o"])
    end = F.when(same < 0, whole).otherwise(F.least(own, other) - 1)
    return both.select("d", "th", (F.col("s") - F.least("lead", "lead0")).alias("s"), (F.col("s") + end).alias("e"))


def repeated_runs(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", min_chars: int = MIN_CHARS) -> DataFrame:
    """(d, th, spans): per document (id, hash of its text) the merged runs of lines to delete."""
    marks = matches(docs, doc_id, text, min_chars).distinct()
    order = W.partitionBy("d", "th").orderBy("s", "e")
    reach = F.max("e").over(order.rowsBetween(W.unboundedPreceding, -1))
    islands = marks.withColumn("fresh", F.when(reach.isNull() | (F.col("s") > reach + 1), 1).otherwise(0))
    islands = islands.withColumn("k", F.sum("fresh").over(order.rowsBetween(W.unboundedPreceding, 0)))
    runs = islands.groupBy("d", "th", "k").agg(F.min("s").cast("int").alias("s"), F.max("e").cast("int").alias("e"))
    return runs.groupBy("d", "th").agg(F.sort_array(F.collect_list(F.struct("s", "e"))).alias("spans"))


def dedup_lines(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", min_chars: int = MIN_CHARS) -> DataFrame:
    """All rows and columns of ``docs`` with the later copies of repeated runs cut from the text, plus
    ld_lines, ld_removed (lines) and ld_spans (columns so named are replaced).

    Null text stays null and counts as one empty line. Rows that repeat an id and its text are one document:
    each comes out alike. A null id orders before all others. Empty tables give empty results.
    """
    f = fresh(docs, "_ld_")
    runs = repeated_runs(docs, doc_id, text, min_chars)
    runs = settle(runs.select(F.col("d").alias(f"{f}d"), F.col("th").alias(f"{f}th"), F.col("spans").alias("ld_spans")))
    plain = F.coalesce(F.col(text), F.lit(""))
    keyed = docs.drop("ld_spans", "ld_lines", "ld_removed").withColumn(f"{f}h", F.xxhash64(plain))
    joined = keyed.join(runs.hint("merge"), F.col(doc_id).eqNullSafe(F.col(f"{f}d")) & (F.col(f"{f}h") == F.col(f"{f}th")), "left")
    joined = joined.withColumn(f"{f}ls", F.split(plain, "\n"))
    size = F.size(f"{f}ls")
    stops = F.concat("ld_spans", F.array(F.struct((size + 1).alias("s"), (size + 1).alias("e"))))
    since = lambda i: F.when(i == 0, 1).otherwise(F.get("ld_spans", i - 1)["e"] + 1)
    keep = F.flatten(F.transform(stops, lambda x, i: F.slice(f"{f}ls", since(i), x["s"] - since(i))))
    out = joined.withColumn(text, F.when(F.col("ld_spans").isNull(), F.col(text)).otherwise(F.concat_ws("\n", keep)))
    gone = F.aggregate("ld_spans", F.lit(0), lambda acc, x: acc + x["e"] - x["s"] + 1)
    out = out.withColumn("ld_lines", size.cast("long")).withColumn("ld_removed", F.coalesce(gone, F.lit(0)).cast("long"))
    return out.drop(*[f + x for x in ("d", "th", "h", "ls")])


def line_query(docs: DataFrame) -> DataFrame:
    """Per document: lines, lines and runs removed, and the hash of the text that is left. Nulls, repeated rows and empty
    tables as in ``dedup_lines``."""
    out = dedup_lines(docs.select("doc_id", "text"))
    return out.select("doc_id", F.col("ld_lines").alias("n_lines"), F.col("ld_removed").alias("n_removed"), F.coalesce(F.size("ld_spans"), F.lit(0)).cast("long").alias("n_spans"), F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


#: From the definition, without fingerprints: w are the windows, r those that occurred before with the first place, m the
#: documents laid over each other at their distance, q the maximal stretches of equal lines, x the part of a stretch around a
#: window that no neighbouring window decides.
ORACLE = f"""
WITH d AS (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS ls FROM documents),
l AS (SELECT doc_id, i, ls[i] AS t, sum(length(ls[i])) OVER (PARTITION BY doc_id ORDER BY i) AS c FROM (SELECT doc_id, ls, unnest(range(1, len(ls) + 1)) AS i FROM d)),
e AS (SELECT a.doc_id, a.i AS s, min(b.i) AS e FROM l a JOIN l b ON a.doc_id = b.doc_id AND b.i >= a.i AND b.c - a.c + length(a.t) >= {MIN_CHARS} WHERE length(a.t) > 0 GROUP BY ALL),
w AS (SELECT e.doc_id, s, e, array_to_string(ls[s:e], chr(10)) AS run, lag(s) OVER o AS before, lead(e) OVER o AS after FROM e JOIN d ON d.doc_id = e.doc_id WINDOW o AS (PARTITION BY e.doc_id ORDER BY s)),
f AS (SELECT run, min((doc_id, s)) AS o FROM w GROUP BY run HAVING count(*) > 1),
r AS (SELECT w.doc_id, w.s, w.e, w.before, w.after, o[1] AS d0, o[2] - w.s AS shift FROM w JOIN f ON w.run = f.run WHERE (w.doc_id, w.s) <> o),
m AS (SELECT p.doc_id, p.d0, p.shift, a.i FROM (SELECT DISTINCT doc_id, d0, shift FROM r) p JOIN l a ON a.doc_id = p.doc_id JOIN l b ON b.doc_id = p.d0 AND b.i = a.i + p.shift AND a.t = b.t),
q AS (SELECT doc_id, d0, shift, min(i) AS s, max(i) AS e FROM (SELECT *, i - row_number() OVER (PARTITION BY doc_id, d0, shift ORDER BY i) AS k FROM m) GROUP BY doc_id, d0, shift, k),
x AS (SELECT DISTINCT q.doc_id, unnest(range(greatest(q.s, coalesce(before, 0) + 1), least(q.e, coalesce(after, q.e)) + 1)) AS i
      FROM q JOIN r ON q.doc_id = r.doc_id AND q.d0 = r.d0 AND q.shift = r.shift AND q.s <= r.s AND q.e >= r.e),
g AS (SELECT doc_id, count(*) AS n, count(*) FILTER (WHERE p IS NULL OR i > p + 1) AS spans, list(i) AS del
      FROM (SELECT doc_id, i, lag(i) OVER (PARTITION BY doc_id ORDER BY i) AS p FROM x) GROUP BY doc_id)
SELECT d.doc_id, len(ls)::BIGINT AS n_lines, coalesce(n, 0)::BIGINT AS n_removed, coalesce(spans, 0)::BIGINT AS n_spans,
  sha256(array_to_string(list_transform(list_filter(range(1, len(ls) + 1), lambda j: NOT list_contains(coalesce(del, []), j)), lambda j: ls[j]), chr(10))) AS kept_sha256
FROM d LEFT JOIN g ON d.doc_id = g.doc_id
"""
