"""Near-duplicate embeddings by p-stable hashing.

Normalised vectors fall into buckets of quantised random projections, m per table, in T tables. Vectors that
meet in a bucket (and share the label) are compared by exact cosine in double precision. m grows with the
logarithm of the largest label so that chance meetings stay few; T follows from m so that a pair at the
threshold meets with probability ``recall``. A pair is counted in the first table where it meets.

Equal vectors form one class. A bucket of any size is dealt out as pairs of blocks of bounded size; a block pair
emits link counts per vector and a spanning forest of its links, never the pairs themselves.
"""

from __future__ import annotations

from math import erf, exp, log, pi, sqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fadedhh.shipping import arrow_map

from . import textbytes as tb
from .common import connected_components, settle

THRESHOLD = 0.93
WIDTH = 2.5
RECALL = 0.999
BLOCK = 512


def meeting(distance: float, width: float) -> float:
    """Chance that two points at a distance share one quantised Gaussian projection."""
    c = distance / width
    return erf(1 / (c * sqrt(2))) - sqrt(2 / pi) * c * (1 - exp(-1 / (2 * c * c)))


def plan(rows: int, threshold: float = THRESHOLD, width: float = WIDTH, recall: float = RECALL, bucket: int = 64) -> tuple[int, int]:
    """(projections per table, tables) for the size of the largest label."""
    far, near = meeting(sqrt(2), width), meeting(sqrt(2 - 2 * threshold), width)
    m = max(4, round(log(max(rows, 2) / bucket) / -log(far)))
    return m, max(1, -(-log(1 - recall) // log(1 - near**m)).__int__())


def _matrix(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(unit vectors in double precision padded with zeros, which are valid)."""
    n = len(column)
    flat = column.flatten()
    size = np.nan_to_num(column.value_lengths().to_numpy(zero_copy_only=False).astype(float)).astype(int)
    dim = int(size.max(initial=0))
    x = np.zeros((n, dim))
    values = flat.cast(pa.float64()).to_numpy(zero_copy_only=False)
    x[np.repeat(np.arange(n), size), np.arange(len(values)) - np.repeat(np.cumsum(size) - size, size)] = values
    ok = np.isfinite(x).all(axis=1)
    x[~ok] = 0
    top = np.abs(x).max(axis=1, initial=0)
    x /= np.where(top > 0, top, 1)[:, None]
    norm = np.linalg.norm(x, axis=1)
    ok &= norm > 0
    return x / np.where(norm > 0, norm, 1)[:, None], ok


def projections(dim: int, count: int, seed: int = 5) -> np.ndarray:
    """Standard normal numbers, each from the counter of its own row and column: every task has the same without sharing
    a table, and longer vectors only add rows."""
    at = (np.arange(count, dtype=np.uint64)[None, :] << np.uint64(32)) + np.arange(dim, dtype=np.uint64)[:, None]
    u, v = ((tb.mix64((np.uint64(2) * at + np.uint64(k)) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(seed)) >> np.uint64(11)).astype(float) / 2**53 for k in (1, 2))
    return np.sqrt(-2 * np.log(1 - u)) * np.cos(2 * pi * v)


def _keys(x: np.ndarray, m: int, tables: int, width: float) -> np.ndarray:
    dim = x.shape[1]
    shift = (tb.mix64(np.arange(1, m * tables + 1, dtype=np.uint64) + np.uint64(99)) >> np.uint64(11)).astype(float) / 2**53
    cell = np.floor(x @ projections(dim, m * tables) / width + shift).astype(np.int64).astype(np.uint64).reshape(len(x), tables, m)
    key = np.zeros((len(x), tables), np.uint64)  # folded to 31 bits at the end: two cells that fall together only meet
    for i in range(m):
        key = tb.mix64(key * np.uint64(3) + cell[:, :, i])
    return (key >> np.uint64(33)).astype(np.int32)


def _links(group: pa.Table, threshold: float) -> pa.Table | None:
    """Counts and forest of one block pair."""
    own = group.column("own").to_numpy()
    table = int(group.column("tb")[0].as_py())
    rep, mult, side = (group.column(c).to_numpy() for c in ("rep", "mult", "side"))
    if len(rep) < 2:
        return None
    keys = np.array(group.column("keys").combine_chunks().flatten()).reshape(len(rep), -1)[:, :table]
    x = _matrix(group.column("vec").combine_chunks())[0]
    whole = bool(own[0])
    a = np.arange(len(rep)) if whole else np.flatnonzero(side == 0)
    b = a if whole else np.flatnonzero(side == 1)
    if not len(a) or not len(b):
        return None
    near = x[a] @ x[b].T >= threshold
    if whole:
        np.fill_diagonal(near, False)
    for t in range(table):
        near &= keys[a, t][:, None] != keys[b, t][None, :]
    if not near.any():
        return None
    count = np.zeros(len(rep), np.int64)
    count[a] += near @ mult[b]
    if not whole:
        count[b] += near.T @ mult[a]
    root = np.arange(len(rep))
    while True:
        new = root.copy()
        low = np.where(near, root[b][None, :], len(rep)).min(axis=1)
        new[a] = np.minimum(new[a], low)
        low = np.where(near, new[a][:, None], len(rep)).min(axis=0)
        new[b] = np.minimum(new[b], low)
        if (new == root).all():
            break
        root = new
    hit = np.flatnonzero(count > 0)
    return pa.table([pa.array(rep[hit]), pa.array(rep[root[hit]]), pa.array(count[hit])], names=["a", "b", "c"])


def _grouped(batches, threshold: float):
    """Streams block pairs (rows arrive sorted by them); what is held never exceeds one block pair and a batch."""
    names = ("tb", "key", "label", "bi", "bj")
    held = None
    out: list = []

    def flush(t: pa.Table, last: bool):
        cols = [t.column(c).to_numpy() for c in names]
        change = np.flatnonzero(np.logical_or.reduce([c[1:] != c[:-1] for c in cols])) + 1
        edges = np.concatenate([[0], change, [t.num_rows]])
        stop = len(edges) - 1 if last else len(edges) - 2
        got = [g for i in range(stop) if edges[i + 1] - edges[i] > 1 and (g := _links(t.slice(edges[i], edges[i + 1] - edges[i]), threshold)) is not None]
        return got, t.slice(edges[stop])

    for b in batches:
        t = pa.Table.from_batches([b])
        t = t if held is None else pa.concat_tables([held, t]).combine_chunks()
        out, held = flush(t, False)
        if out:
            yield from pa.concat_tables(out).to_batches()
    if held is not None and held.num_rows:
        out, _ = flush(held, True)
        if out:
            yield from pa.concat_tables(out).to_batches()


def link_vectors(emb: DataFrame, vec_id: str = "vec_id", vector: str = "embedding", label: str = "label", threshold: float = THRESHOLD, width: float = WIDTH, recall: float = RECALL, block: int = BLOCK) -> DataFrame:
    """(vec_id, n_links, component_id, kept) for every row.

    Labels of any type are compared by a 64-bit hash. Null labels, null or zero vectors and vectors with null or non-finite parts link with nothing. Shorter vectors
    count as padded with zeros. Rows that repeat an id count as vectors of their own. A row without id links
    like others but names no component; it gets its component or null. Empty tables give empty results.
    """
    rows = emb.select(F.col(vec_id).cast("long").alias("id"), F.col(vector).alias("vec"), F.when(F.col(label).isNotNull(), F.xxhash64(label)).alias("label"))
    sound = F.col("label").isNotNull() & F.col("vec").isNotNull() & F.coalesce(F.exists("vec", lambda x: x != 0), F.lit(False)) & ~F.exists("vec", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    rows = rows.withColumn("ok", F.coalesce(sound, F.lit(False)))
    kind = dict(rows.dtypes)["vec"]
    d = settle(rows.withColumn("h", F.when(F.col("ok"), F.xxhash64("vec"))).withColumn("g", F.when(F.col("ok"), F.xxhash64(F.lit(3), "vec"))))
    classes = settle(d.where("ok and id is not null").groupBy("label", "h", "g").agg(F.min("id").alias("rep"), F.count("*").alias("mult"), F.first("vec").alias("vec")))
    most = classes.groupBy("label").agg(F.count("*").alias("n")).agg(F.max("n")).first()[0] or 0
    m, tables = plan(most, threshold, width, recall)

    def hashed(batches):
        for b in batches:
            x, _ = _matrix(b.column(3))
            k = _keys(x, m, tables, width)
            off = pa.array(np.arange(0, tables * (len(k) + 1), tables).astype(np.int32))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.ListArray.from_arrays(off, pa.array(k.reshape(-1)))], names=["label", "rep", "mult", "vec", "keys"])

    keyed = settle(arrow_map(classes.select("label", "rep", "mult", "vec"), hashed, f"label long, rep long, mult long, vec {kind}, keys array<int>"))
    spread = keyed.select("label", "rep", F.posexplode("keys").alias("tb", "key"))
    shared = settle(spread.groupBy("label", "tb", "key").agg(F.count("*").alias("size")).where("size > 1"))
    member = spread.join(shared.hint("merge"), ["label", "tb", "key"])
    member = member.withColumn("nb", F.ceil(F.col("size") / block).cast("int")).withColumn("mine", F.pmod(F.xxhash64("rep"), F.col("nb")).cast("int"))
    dealt = member.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("nb") - 1)))
    dealt = dealt.select("rep", "label", "tb", "key", F.least("mine", "other").alias("bi"), F.greatest("mine", "other").alias("bj"), F.when(F.col("mine") <= F.col("other"), 0).otherwise(1).alias("side"), (F.col("mine") == F.col("other")).alias("own_"))
    full = dealt.join(keyed.select("rep", "mult", "vec", "keys").hint("merge"), "rep")
    full = full.select("tb", "key", "label", "bi", "bj", "side", (F.col("bi") == F.col("bj")).alias("own"), "rep", "mult", "vec", "keys")
    parts = int(emb.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    full = full.repartition(parts, "tb", "key", "label", "bi", "bj").sortWithinPartitions("tb", "key", "label", "bi", "bj")
    links = settle(arrow_map(full, lambda it: _grouped(it, threshold), "a long, b long, c long"))
    count = links.groupBy(F.col("a").alias("rep")).agg(F.sum("c").alias("c"))
    comp = connected_components(links).select(F.col("node").alias("rep"), "comp")
    place = settle(classes.select("label", "h", "g", "rep", "mult").join(count, "rep", "left").join(comp, "rep", "left").select(F.col("label").alias("cl"), F.col("h").alias("ch"), F.col("g").alias("cg"), F.coalesce("comp", "rep").alias("comp"), (F.coalesce("c", F.lit(0)) + F.col("mult") - 1).alias("links")))
    res = d.select("id", "label", "h", "g").join(place.hint("merge"), F.expr("label = cl and h = ch and g = cg"), "left")
    component = F.coalesce("comp", "id")
    return res.select(F.col("id").alias("vec_id"), F.coalesce("links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(F.col("id") == component, F.lit(False)).alias("kept"))


ORACLE = f"""
WITH RECURSIVE v AS (SELECT vec_id, label, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings WHERE label IS NOT NULL AND embedding IS NOT NULL),
u AS (SELECT vec_id, label, e, sqrt(list_sum(list_transform(e, lambda x: x * x))) AS n FROM v),
l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM u a JOIN u b ON a.label = b.label AND a.vec_id <> b.vec_id
      WHERE a.n > 0 AND b.n > 0 AND list_dot_product(a.e, b.e) / (a.n * b.n) >= {THRESHOLD}),
r AS (SELECT vec_id AS node, vec_id AS seen FROM embeddings UNION SELECT r.node, l.b FROM r JOIN l ON r.seen = l.a),
m AS (SELECT node, min(seen) AS c FROM r GROUP BY node), k AS (SELECT a, count(*) AS n FROM l GROUP BY a)
SELECT e.vec_id, coalesce(k.n, 0)::BIGINT AS n_links, m.c AS component_id, m.c = e.vec_id AS kept
FROM embeddings e JOIN m ON m.node = e.vec_id LEFT JOIN k ON k.a = e.vec_id
"""
