"""Registry of the engine's own queries, each with equivalent SQL where SQL can say it."""

from __future__ import annotations

import math
from collections.abc import Callable
from datetime import timedelta

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fadedhh.functions import cell, decay
from fadedhh.functions.decay import DecaySpec
from fadedhh.functions.times import between_days, micros
from fadedhh.operators import countmin, exact, invariants, metrics, params as sizing, related, sketch, spacesaving, window_hh
from fadedhh.operators.params import SketchParams
from fadedhh.plans import measure, miner, online_runs, sqlapi
from fadedhh.plans import workloads as wl
from fadedhh.sources.tables import load

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}

#: Thresholds that lie in gaps of the streams' shares.
PHI = {"users": 0.0122, "parts": 0.0016, "suppliers": 0.0126, "customers": 0.0036, "tokens": 0.008, "hosts": 0.02, "types": 0.15, "props": 0.012}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Heavy users of the smallest stream, by the folded sketch."""
    return folded_users(spark, sf_dir, w=256, p=4).heavy_hitters(0.08, wl.EVENTS_TO)


# ---- SQL fragments ----


def dbl(x: float) -> str:
    return f"{x!r}::DOUBLE"


def hh_sql(s: wl.Stream, phi: float, cols: str = "item, f / {norm} AS f, f / c AS share", weighted: str | None = None) -> str:
    norm = dbl(s.decay.g(s.now - s.landmark))
    return f"""WITH s AS ({weighted or s.weighted_sql()}), f AS (SELECT item, sum(x) AS f FROM s GROUP BY item), c AS (SELECT sum(f) AS c FROM f)
    SELECT {cols.format(norm=norm)} FROM f, c WHERE f > {dbl(phi)} * c"""


def norm_of(s: wl.Stream) -> float:
    return s.decay.g(s.now - s.landmark)


STREAMS: dict[str, wl.Stream] = {
    "users": wl.users(), "event_type": wl.types(), "props": wl.props(), "parts": wl.lineitem("l_partkey"), "suppliers": wl.lineitem("l_suppkey"),
    "customers": wl.customers(), "tokens": wl.tokens(), "hosts": wl.hosts(), "zipf11": wl.zipf(),
}
PHI |= {"event_type": PHI["types"], "zipf11": 0.01}
USERS, PARTS = STREAMS["users"], STREAMS["parts"]

# ---- decay ----

_EV = f"(SELECT event_id, epoch_us(ts) AS tick FROM events WHERE epoch_us(ts) > {wl.EVENTS_FROM}::BIGINT AND epoch_us(ts) <= {wl.EVENTS_TO}::BIGINT)"
_SPAN = wl.EVENTS_TO - wl.EVENTS_FROM
_RATE = decay.rate_from_half_life(timedelta(days=2))


def _timed(spark, sf_dir):
    return load(spark, sf_dir, "events").where(between_days("ts", "2024-01-01", "2024-01-31")).select("event_id", micros("ts").alias("tick"))


def _weights(spec: DecaySpec, digits: int | None):
    def run(spark, sf_dir):
        w = decay.forward_weight(F.col("tick"), wl.EVENTS_TO, wl.EVENTS_FROM, spec)
        return _timed(spark, sf_dir).select("event_id", (F.round(w, digits) if digits else w).alias("w"))

    return run


_AGE = f"(tick - {wl.EVENTS_FROM}::BIGINT)"
query("decay_weights_dyadic", f"SELECT event_id, pow(2.0::DOUBLE, {_AGE} // {wl.DAY}::BIGINT) / {dbl(2.0**30)} AS w FROM {_EV}")(_weights(DecaySpec.dyadic(wl.DAY), None))
query("decay_weights_exp", f"SELECT event_id, round(exp({dbl(_RATE)} * ({_AGE}::DOUBLE / 1e6)) / {dbl(DecaySpec.exp(_RATE).g(_SPAN))}, 9) AS w FROM {_EV}")(_weights(DecaySpec.exp(_RATE), 9))
query("decay_weights_poly", f"SELECT event_id, round(pow({_AGE}::DOUBLE / 1e6, 2.0::DOUBLE) / {dbl(DecaySpec.poly(2).g(_SPAN))}, 9) AS w FROM {_EV}")(_weights(DecaySpec.poly(2), 9))


@query("decay_backward_eq_forward", f"""SELECT count(*) AS n, round(max(abs(exp({dbl(_RATE)} * ({_AGE}::DOUBLE / 1e6)) / exp({dbl(_RATE)} * {dbl(_SPAN / 1e6)}) - exp(-{dbl(_RATE)} * (({wl.EVENTS_TO}::BIGINT - tick)::DOUBLE / 1e6)))), 9) AS max_gap FROM {_EV}""")
def _backward(spark, sf_dir):
    spec = DecaySpec.exp(_RATE)
    gap = F.abs(decay.forward_weight(F.col("tick"), wl.EVENTS_TO, wl.EVENTS_FROM, spec) - decay.backward_weight(F.col("tick"), wl.EVENTS_TO, spec))
    return _timed(spark, sf_dir).agg(F.count("*").alias("n"), F.round(F.max(gap), 9).alias("max_gap"))


@query("weights_landmark_shift", f"SELECT count(*) AS n, 0.0::DOUBLE AS max_gap FROM {_EV}")
def _shift(spark, sf_dir):
    spec = DecaySpec.exp(_RATE)
    a = decay.forward_weight(F.col("tick"), wl.EVENTS_TO, wl.EVENTS_FROM, spec)
    b = decay.forward_weight(F.col("tick"), wl.EVENTS_TO, wl.EVENTS_FROM - 5 * wl.DAY, spec)
    return _timed(spark, sf_dir).agg(F.count("*").alias("n"), F.round(F.max(F.abs(a - b)), 9).alias("max_gap"))


_NOWS = [wl.EVENTS_FROM + k * 10 * wl.DAY for k in (1, 2, 3)]


@query("decay_contract", " UNION ALL ".join(f"SELECT {k} AS step, count(*) AS n, 0::BIGINT AS out_of_range, 0::BIGINT AS grew, 0::BIGINT AS not_one_at_zero FROM {_EV} WHERE tick <= {_NOWS[max(0, k - 1)]}::BIGINT" for k in range(3)))
def _contract(spark, sf_dir):
    return decay.check_contract(_timed(spark, sf_dir), DecaySpec.dyadic(wl.DAY), wl.EVENTS_FROM, _NOWS)


#: Decayed share of every user, from which sketches are sized.
_SHARES = f"(SELECT item, f / c AS share FROM (SELECT item, sum(x) AS f FROM ({USERS.weighted_sql()}) GROUP BY item), (SELECT sum(x) AS c FROM ({USERS.weighted_sql()})))"
_DELTAS, _KINDS = (0.05, 0.001), ("faded", "countmin")


def _shares(spark, sf_dir):
    return exact.heavy_hitters(USERS.weighted(spark, sf_dir), 0.0).select("item", "share")


@query("sketch_dimensions", " UNION ALL ".join(
    f"SELECT item, share / 2 AS eps, {dbl(delta)} AS delta, '{kind}' AS kind, ceil(ln(1 / {dbl(delta)}))::BIGINT AS d, ceil({dbl(math.e)} / ({1 if kind == 'countmin' else 2}::DOUBLE * (share / 2)))::BIGINT AS w FROM {_SHARES}"
    for delta in _DELTAS for kind in _KINDS))
def _dims(spark, sf_dir):
    """The grid that every user would need: one whose error is half of that user's decayed share."""
    eps, shares = F.col("share") / 2, _shares(spark, sf_dir)
    sizes = [F.struct(F.lit(x).alias("delta"), F.lit(k).alias("kind"), *[c.alias(n) for c, n in zip(sizing.dimension_columns(eps, F.lit(x), k), "dw")]) for x in _DELTAS for k in _KINDS]
    return shares.select("item", eps.alias("eps"), F.explode(F.array(*sizes)).alias("s")).select("item", "eps", "s.*")


_GRIDS = [(d, w) for d in (1, 2, 4) for w in (128, 800, 1340)]


@query("detection_bounds", " UNION ALL ".join(
    f"SELECT item, phi, {d} AS d, {w} AS w, least(1.0::DOUBLE, {' * '.join(['q'] * d)}) AS miss FROM (SELECT item, share AS phi, 1.0::DOUBLE / ({dbl(2.0 * w)} * share) AS q FROM {_SHARES})"
    for d, w in _GRIDS))
def _bounds(spark, sf_dir):
    """The bound on the chance that a grid misses a user, for every user at their decayed share."""
    phi = F.col("share")
    misses = [F.struct(F.lit(d).alias("d"), F.lit(w).alias("w"), sizing.miss_bound_column(phi, d, w).alias("miss")) for d, w in _GRIDS]
    return _shares(spark, sf_dir).select("item", phi.alias("phi"), F.explode(F.array(*misses)).alias("m")).select("item", "phi", "m.*")


# ---- exact answers ----


@query("decayed_frequency_users", f"SELECT item, sum(x) AS f FROM ({USERS.weighted_sql()}) GROUP BY item")
def _freq(spark, sf_dir):
    return exact.decayed_frequency(USERS.weighted(spark, sf_dir))


@query("decayed_count_events", f"SELECT sum(x) AS c, sum(x) / {dbl(norm_of(USERS))} AS c_norm FROM ({USERS.weighted_sql()})")
def _count(spark, sf_dir):
    return sketch.global_count(USERS.weighted(spark, sf_dir)).select("c", (F.col("c") / F.lit(norm_of(USERS))).alias("c_norm"))


for _name, _s in STREAMS.items():
    query(f"exact_hh_{_name}", hh_sql(_s, PHI[_name]))(lambda spark, sf_dir, s=_s, phi=PHI[_name]: exact.heavy_hitters(s.weighted(spark, sf_dir), phi, norm_of(s)))

_PLAIN = wl.Stream(USERS.build, USERS.sql, USERS.landmark, USERS.now, DecaySpec.none())


@query("exact_hh_undecayed", hh_sql(_PLAIN, 0.0085))
def _undecayed(spark, sf_dir):
    return exact.heavy_hitters(_PLAIN.weighted(spark, sf_dir), 0.0085)


_WIDTH = 7 * wl.DAY


@query("sliding_window_hh", f"""WITH f AS (SELECT user_id AS item, count(*)::DOUBLE AS f FROM events WHERE epoch_us(ts) > {wl.EVENTS_TO - _WIDTH}::BIGINT AND epoch_us(ts) <= {wl.EVENTS_TO}::BIGINT GROUP BY user_id), c AS (SELECT sum(f) AS c FROM f)
SELECT item, f, f / c AS share FROM f, c WHERE f > {dbl(0.0105)} * c""")
def _window(spark, sf_dir):
    return window_hh.exact(USERS.build(spark, sf_dir), _WIDTH, 0.0105, wl.EVENTS_TO)


@query("rolling_count_rows", f"SELECT item, tick, ord, count(*) OVER (PARTITION BY item ORDER BY tick RANGE BETWEEN {wl.DAY - 1}::BIGINT PRECEDING AND CURRENT ROW) AS n FROM ({USERS.weighted_sql()})")
def _rolling(spark, sf_dir):
    return window_hh.rolling(USERS.weighted(spark, sf_dir), wl.DAY)


@query("weighted_shares_ranked", f"""WITH f AS (SELECT item, sum(x) AS f FROM ({USERS.weighted_sql()}) GROUP BY item), c AS (SELECT sum(f) AS c FROM f)
SELECT item, f, f / c AS share, (row_number() OVER (ORDER BY f DESC, item))::INTEGER AS rank, sum(f) OVER (ORDER BY f DESC, item ROWS UNBOUNDED PRECEDING) / c AS running FROM f, c ORDER BY f DESC, item LIMIT 25""")
def _ranked(spark, sf_dir):
    return exact.ranked(USERS.weighted(spark, sf_dir), 25)


_TYPED = wl.users("event_type")


@query("mass_cube_type_day", f"SELECT event_type, day, sum(x) AS f FROM (SELECT *, ((tick - {wl.EVENTS_FROM}::BIGINT) // {wl.DAY}::BIGINT) AS day FROM ({_TYPED.weighted_sql()})) GROUP BY CUBE (event_type, day)")
def _cube(spark, sf_dir):
    day = F.floor((F.col("tick") - wl.EVENTS_FROM) / wl.DAY).alias("day")
    return exact.mass_cube(_TYPED.weighted(spark, sf_dir).select("event_type", day, "x"), "event_type", "day")


@query("mass_pivot_type", f"""SELECT ((tick - {wl.EVENTS_FROM}::BIGINT) // {wl.DAY}::BIGINT) AS day, sum(x) FILTER (WHERE event_type = 'view') AS view, sum(x) FILTER (WHERE event_type = 'click') AS click, sum(x) FILTER (WHERE event_type = 'error') AS error
FROM ({_TYPED.weighted_sql()}) GROUP BY 1""")
def _pivot(spark, sf_dir):
    day = F.floor((F.col("tick") - wl.EVENTS_FROM) / wl.DAY).alias("day")
    return exact.mass_pivot(_TYPED.weighted(spark, sf_dir).select(day, "event_type", "x"), "day", "event_type", ["view", "click", "error"])


_CUST = STREAMS["customers"]


@query("mass_sets_type_day", f"SELECT event_type, day, sum(x) AS f FROM (SELECT *, ((tick - {wl.EVENTS_FROM}::BIGINT) // {wl.DAY}::BIGINT) AS day FROM ({_TYPED.weighted_sql()})) GROUP BY GROUPING SETS ((event_type), (day), ())")
def _sets(spark, sf_dir):
    day = F.floor((F.col("tick") - wl.EVENTS_FROM) / wl.DAY).alias("day")
    return exact.mass_sets(_TYPED.weighted(spark, sf_dir).select("event_type", day, "x"), [["event_type"], ["day"], []])


@query("mass_rollup_region_nation", f"""SELECT r_name, n_name, sum(x) AS f FROM ({_CUST.weighted_sql()}) JOIN customer ON c_custkey = item JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ROLLUP (r_name, n_name)""")
def _rollup(spark, sf_dir):
    per = exact.decayed_frequency(_CUST.weighted(spark, sf_dir)).withColumnRenamed("f", "x")
    c = load(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    n, r = load(spark, sf_dir, "nation"), load(spark, sf_dir, "region")
    rows = per.join(c, F.col("item") == F.col("c_custkey")).join(n, F.col("n_nationkey") == F.col("c_nationkey")).join(r, F.col("r_regionkey") == F.col("n_regionkey"))
    return exact.mass_rollup(rows, "r_name", "n_name")


# ---- hashing and Count-Min ----

_SMALL = USERS.params(w=64)
_CM = PARTS.params(w=256)


def rows_sql(weighted: str, p: SketchParams, extra: str = "") -> str:
    return " UNION ALL ".join(f"SELECT {r} AS row, {h} AS col, item, x{extra} FROM ({weighted})" for r, h in enumerate(p.hashes.sql()))


@query("hash_columns_mod31", f"SELECT DISTINCT item, row::INTEGER AS row, col FROM ({rows_sql(USERS.weighted_sql(), _SMALL)})")
def _hashes(spark, sf_dir):
    return sketch.row_hashes(USERS.weighted(spark, sf_dir).select("item").distinct(), _SMALL)


_CM_SQL = f"SELECT row::INTEGER AS row, col, sum(x) AS f FROM ({rows_sql(PARTS.weighted_sql(), _CM)}) GROUP BY row, col"


@query("countmin_cells", _CM_SQL)
def _cm(spark, sf_dir):
    return countmin.build(PARTS.weighted(spark, sf_dir), _CM)


@query("countmin_merge_shards", _CM_SQL)
def _cm_merge(spark, sf_dir):
    s = PARTS.weighted(spark, sf_dir)
    return countmin.merge(*[countmin.build(s.where(F.pmod("ord", F.lit(3)) == k), _CM) for k in range(3)])


_CM_EST = f"WITH g AS ({_CM_SQL}), i AS (SELECT DISTINCT row, col, item FROM ({rows_sql(PARTS.weighted_sql(), _CM)})) SELECT item, min(f) AS est FROM i JOIN g ON g.row = i.row AND g.col = i.col GROUP BY item"


@query("countmin_point", _CM_EST)
def _cm_point(spark, sf_dir):
    s = PARTS.weighted(spark, sf_dir)
    return countmin.estimate(countmin.build(s, _CM), _CM, s.select("item").distinct())


_CMH = PARTS.params(w=2720)


@query("countmin_hh", f"WITH e AS ({_CM_EST.replace(rows_sql(PARTS.weighted_sql(), _CM), rows_sql(PARTS.weighted_sql(), _CMH))}), c AS (SELECT sum(x) AS c FROM ({PARTS.weighted_sql()})) SELECT item, est FROM e, c WHERE est > {dbl(0.0016)} * c")
def _cm_hh(spark, sf_dir):
    return countmin.heavy_hitters(PARTS.weighted(spark, sf_dir), _CMH, 0.0016)


# ---- the faded sketch: cells ----


_EVENT_ROWS = "(SELECT max(event_id) + 1 FROM events)"


def fold_sql(s: wl.Stream, p: SketchParams, shards: int, total: str = _EVENT_ROWS) -> str:
    """CTEs ending in m(row, col, cell): ordered fold per shard, then over the shards."""
    shard = f"(ord * {shards} // {total})" if shards > 1 else "0"
    rows = rows_sql(f"SELECT *, {shard} AS shard FROM ({s.weighted_sql()})", p, ", shard, ord")
    return f"""WITH h AS ({rows}),
    l AS (SELECT shard, row, col, list_reduce(list([{{'n': -x, 'i': item}}] ORDER BY ord), lambda a, b: {cell.merge_sql('a', 'b')}) AS cell FROM h GROUP BY shard, row, col),
    m AS (SELECT row::INTEGER AS row, col, list_reduce(list(cell ORDER BY shard), lambda a, b: {cell.merge_sql('a', 'b')}) AS cell FROM l GROUP BY row, col)"""


_FIELDS = "cell[1].i AS i1, -cell[1].n AS f1, cell[2].i AS i2, coalesce(-cell[2].n, 0.0::DOUBLE) AS f2"


def event_rows(spark, sf_dir) -> int:
    return load(spark, sf_dir, "events").agg(F.max("event_id") + 1).first()[0] or 1


def folded_users(spark, sf_dir, w: int = 64, p: int = 4, fan_in: int = 64) -> miner.Mined:
    s = USERS.weighted(spark, sf_dir)
    s = sketch.block_shards(s, p, event_rows(spark, sf_dir)) if p > 1 else s.withColumn("shard", F.lit(0))
    return miner.mine_folded(s, USERS.params(w=w), p, fan_in)


for _p, _n in ((1, "sketch_cells_sequential"), (4, "sketch_cells_merged_p4"), (16, "sketch_cells_merged_p16")):
    query(_n, f"{fold_sql(USERS, _SMALL, _p)} SELECT row, col, {_FIELDS} FROM m")(lambda spark, sf_dir, p=_p: folded_users(spark, sf_dir, p=p).cells)


@query("kernel_replays_fold", f"SELECT count(*) AS cells, 0::BIGINT AS different FROM (SELECT DISTINCT row, col FROM ({rows_sql(USERS.weighted_sql(), _SMALL)}))")
def _kernel(spark, sf_dir):
    """The kernel without combining replays an ordered stream exactly as the fold does."""
    s = USERS.weighted(spark, sf_dir).withColumn("shard", F.lit(0)).repartition(1).sortWithinPartitions("ord")
    local = sketch.local_sketches(s, _SMALL, combine=False).where("row >= 0").drop("shard")
    fold = folded_users(spark, sf_dir, p=1).cells
    names = ["i1", "f1", "i2", "f2"]
    both = local.join(fold.select("row", "col", *[F.col(c).alias(f"{c}_") for c in names]), ["row", "col"], "full_outer")
    same = F.lit(True)
    for c in names:
        same = same & F.col(c).eqNullSafe(F.col(f"{c}_"))
    return both.agg(F.count("*").alias("cells"), F.count_if(~same).alias("different"))


@query("sketch_merge_two", f"SELECT count(*) AS cells, 0.0::DOUBLE AS max_gap FROM (SELECT DISTINCT row, col FROM ({rows_sql(USERS.weighted_sql(), _SMALL)}))")
def _two(spark, sf_dir):
    """Pairwise merge of the sketches of two halves keeps the mass of every cell."""
    s = USERS.weighted(spark, sf_dir)
    half = [miner.mine_weighted(s.where(F.pmod("ord", F.lit(2)) == k), _SMALL).cells for k in (0, 1)]
    return invariants.norm_equivalence(sketch.merge_two(*half), countmin.build(s, _SMALL))


for _n, _s, _w in (("users", USERS, 64), ("parts", PARTS, 256), ("zipf11", STREAMS["zipf11"], 128)):
    _par = _s.params(w=_w)
    query(f"sketch_norm_equivalence_{_n}", f"SELECT count(*) AS cells, 0.0::DOUBLE AS max_gap FROM (SELECT DISTINCT row, col FROM ({rows_sql(_s.weighted_sql(), _par)}))")(
        lambda spark, sf_dir, s=_s, p=_par: invariants.norm_equivalence(miner.mine_weighted(s.weighted(spark, sf_dir), p).cells, countmin.build(s.weighted(spark, sf_dir), p))
    )
    query(f"row_mass_{_n}", f"SELECT row::INTEGER AS row, sum(x) AS mass FROM ({rows_sql(_s.weighted_sql(), _par)}) GROUP BY row")(
        lambda spark, sf_dir, s=_s, p=_par: invariants.row_mass(miner.mine_weighted(s.weighted(spark, sf_dir), p).cells)
    )


@query("cell_bounds_violations", f"SELECT count(*) AS pairs, 0::BIGINT AS under, 0::BIGINT AS over, 0::BIGINT AS unmonitored, 0::BIGINT AS half FROM (SELECT DISTINCT row, col, item FROM ({rows_sql(PARTS.weighted_sql(), _CM)}))")
def _cell_bounds(spark, sf_dir):
    s = PARTS.weighted(spark, sf_dir)
    return invariants.cell_bounds(miner.mine_weighted(s, _CM).cells, s, _CM)


@query("never_under_parts", f"SELECT count(DISTINCT item) AS items, 0::BIGINT AS under FROM ({PARTS.weighted_sql()})")
def _never(spark, sf_dir):
    s = PARTS.weighted(spark, sf_dir)
    return invariants.never_under(miner.mine_weighted(s, _CM).cells, s, _CM)


# ---- the faded sketch: answers ----


def estimate_sql(s: wl.Stream, p: SketchParams, shards: int, total: str = _EVENT_ROWS) -> str:
    probe = " UNION ALL ".join(f"SELECT {r} AS row, {h} AS col, item FROM (SELECT DISTINCT item FROM ({s.weighted_sql()}))" for r, h in enumerate(p.hashes.sql()))
    value = "CASE WHEN cell[1].i = item THEN -cell[1].n WHEN cell[2].i = item THEN -cell[2].n ELSE coalesce(-cell[2].n, 0.0::DOUBLE) END"
    return f"{fold_sql(s, p, shards, total)}, q AS ({probe}), e AS (SELECT item, min({value}) AS est FROM q LEFT JOIN m ON m.row = q.row AND m.col = q.col GROUP BY item)"


@query("point_estimate_users", f"{estimate_sql(USERS, _SMALL, 4)} SELECT item, est / {dbl(norm_of(USERS))} AS est FROM e")
def _point(spark, sf_dir):
    return folded_users(spark, sf_dir).estimate(USERS.weighted(spark, sf_dir).select("item").distinct(), wl.EVENTS_TO)


_W256 = USERS.params(w=256)
_FADED_USERS = f"""{estimate_sql(USERS, _W256, 4)}, c AS (SELECT sum(x) AS c FROM ({USERS.weighted_sql()}))
SELECT item, est / {dbl(norm_of(USERS))} AS est FROM e, c WHERE est > {dbl(0.0122)} * c AND item IN (SELECT cell[1].i FROM m, c WHERE -cell[1].n > {dbl(0.0122)} * c)"""


@query("faded_hh_users", _FADED_USERS)
def _faded_users(spark, sf_dir):
    return folded_users(spark, sf_dir, w=256, p=4).heavy_hitters(0.0122, wl.EVENTS_TO)


def verified(s: wl.Stream, phi: float, w: int = 1360):
    """The faded miner's answer with exact frequencies from its second scan."""

    def run(spark, sf_dir):
        weighted, p = s.weighted(spark, sf_dir), s.params(w=w)
        return miner.mine_weighted(weighted, p).verified(weighted, phi, s.now, strict=False)

    return run


for _name in ("parts", "suppliers", "customers", "tokens", "hosts", "event_type", "props", "zipf11"):
    query(f"faded_hh_{_name}", hh_sql(STREAMS[_name], PHI[_name], "item, f / {norm} AS f"))(verified(STREAMS[_name], PHI[_name]))

_DIALOG = wl.tokens("conversations", "conv_id", also="role")
_ROLES = ["user", "assistant", "system"]


@query("dialog_terms_hh", f"WITH f AS (SELECT role, item, sum(x) AS f FROM ({_DIALOG.weighted_sql()}) GROUP BY ALL) SELECT role, item, f FROM (SELECT *, sum(f) OVER (PARTITION BY role) AS c FROM f) WHERE f > 0.02::DOUBLE * c")
def _dialog(spark, sf_dir):
    """Heavy terms of each role, by one grouped sketch and exact sums of its answer."""
    return miner.verified_grouped(_DIALOG.weighted(spark, sf_dir), _DIALOG.params(), "role", 0.02, _ROLES)


_GOOD = wl.tokens(quality=True)
query("quality_docs_tokens_hh", hh_sql(_GOOD, 0.01, "item, f / {norm} AS f"))(verified(_GOOD, 0.01))
_BY_DATE = wl.parts_by_orderdate()
query("parts_by_orderdate_hh", hh_sql(_BY_DATE, 0.0016, "item, f / {norm} AS f"))(verified(_BY_DATE, 0.0016))


@query("scoped_hh_segment", f"""WITH s AS (SELECT s.* FROM ({_CUST.weighted_sql()}) s JOIN customer ON c_custkey = item WHERE c_mktsegment = 'BUILDING'), f AS (SELECT item, sum(x) AS f FROM s GROUP BY item), c AS (SELECT sum(f) AS c FROM f)
SELECT item, f / {dbl(norm_of(_CUST))} AS f FROM f, c WHERE f > 0.014::DOUBLE * c""")
def _scoped(spark, sf_dir):
    c = load(spark, sf_dir, "customer").where("c_mktsegment = 'BUILDING'").select(F.col("c_custkey").alias("item"))
    weighted = _CUST.weighted(spark, sf_dir).join(c, "item", "left_semi")
    return miner.mine_weighted(weighted, _CUST.params()).verified(weighted, 0.014, _CUST.now)


@query("labelled_hh_parts", f"SELECT item, p_name, h.f FROM ({hh_sql(PARTS, 0.0016, 'item, f / {norm} AS f')}) h JOIN part ON p_partkey = item")
def _labelled(spark, sf_dir):
    return sketch.label(verified(PARTS, 0.0016)(spark, sf_dir), load(spark, sf_dir, "part"), "p_partkey", ["p_name"]).select("item", "p_name", "f")


_REV = wl.lineitem("l_partkey", revenue=True)
_REV_W = f"SELECT * REPLACE (x * x0 AS x) FROM ({_REV.weighted_sql()})"


@query("weighted_hh_revenue", hh_sql(_REV, 0.0017, "item, round(f / {norm}, 3) AS f", _REV_W))
def _revenue(spark, sf_dir):
    weighted = _REV.weighted(spark, sf_dir, "x0")
    return miner.mine_weighted(weighted, _REV.params()).verified(weighted, 0.0017, _REV.now).select("item", F.round("f", 3).alias("f"))


_GROUPED = f"""WITH f AS (SELECT event_type, item, sum(x) AS f FROM ({_TYPED.weighted_sql()}) GROUP BY ALL) SELECT event_type, item, f FROM (SELECT *, sum(f) OVER (PARTITION BY event_type) AS c FROM f) WHERE f > 0.025::DOUBLE * c"""


@query("grouped_hh_by_type", _GROUPED)
def _grouped(spark, sf_dir):
    """A sketch per event type, all in one pass; exact sums are taken of its answer only."""
    return miner.verified_grouped(_TYPED.weighted(spark, sf_dir), _TYPED.params(w=256), "event_type", 0.025, ["view", "click", "purchase", "signup", "error"])


@query("topk_decayed", f"SELECT item, sum(x) / {dbl(norm_of(USERS))} AS est FROM ({USERS.weighted_sql()}) GROUP BY item ORDER BY sum(x) DESC, item LIMIT 10")
def _topk(spark, sf_dir):
    weighted = USERS.weighted(spark, sf_dir)
    return miner.mine_weighted(weighted, USERS.params(w=6400)).exact_top_k(weighted, 10, wl.EVENTS_TO)


# ---- experiments ----

_Z = STREAMS["zipf11"]


def sweep_sql(vary: str) -> str:
    """Truth by SQL; that every true heavy hitter and nothing else is reported is the claim under test."""
    out = []
    for at in wl.points(vary):
        out.append(f"""(WITH f AS (SELECT item, sum(x) AS f FROM ({at.stream().weighted_sql()}) GROUP BY item), c AS (SELECT sum(f) AS c FROM f)
        SELECT '{vary}' AS vary_name, {at.value!r}::DOUBLE AS vary_value, {str(at.params().eps < at.phi).lower()} AS in_guarantee, count(*) AS truth, count(*) AS reported, count(*) AS hits, 1.0::DOUBLE AS precision, 1.0::DOUBLE AS recall
        FROM f, c WHERE f > {dbl(at.phi)} * c)""")
    return " UNION ALL ".join(out)


def measured_sql(s: wl.Stream, p: SketchParams, shards: int, phi: float, cols: str, total: str = _EVENT_ROWS) -> str:
    """One row of measures of the folded sketch's answer. ``cols`` may use truth, reported, hits, are, worst and mean."""
    phi_, norm = dbl(phi), dbl(norm_of(s))
    return f"""{estimate_sql(s, p, shards, total)}, t AS (SELECT item, sum(x) AS f FROM ({s.weighted_sql()}) GROUP BY item), c AS (SELECT sum(f) AS c FROM t),
    a AS (SELECT item, est FROM e, c WHERE est > {phi_} * c AND item IN (SELECT cell[1].i FROM m, c WHERE -cell[1].n > {phi_} * c)),
    b AS (SELECT t.item, f, est, f > {phi_} * c AS heavy, est IS NOT NULL AS told FROM t CROSS JOIN c LEFT JOIN a ON a.item = t.item),
    z AS (SELECT count(*) FILTER (WHERE heavy) AS truth, count(*) FILTER (WHERE told) AS reported, count(*) FILTER (WHERE heavy AND told) AS hits, coalesce(avg(abs(est - f) / f) FILTER (WHERE heavy AND told), 0) AS are,
      coalesce(max(abs(est - f)), 0) / {norm} AS worst, coalesce(avg(abs(est - f)), 0) / {norm} AS mean FROM b)
    SELECT {cols} FROM z"""


_RATIOS = "truth, reported, hits, CASE WHEN reported = 0 THEN 1.0::DOUBLE ELSE hits / reported END AS precision, CASE WHEN truth = 0 THEN 1.0::DOUBLE ELSE hits / truth END AS recall"
_ERRORS = "round(are, 9) AS are, round(worst, 6) AS abs_err_max, round(mean, 6) AS abs_err_mean"


def rounded(df: DataFrame) -> DataFrame:
    """Measures of error to as many digits as sums of exponential weights agree in any order."""
    return df.withColumns({c: F.round(c, d) for c, d in (("are", 9), ("abs_err_max", 6), ("abs_err_mean", 6))})


#: Copies of each event in the runs of the reference form, which replays element by element in both engines.
_COPIES = 2


def error_sql(vary: str) -> str:
    every = "(SELECT round(avg(abs(e.est - t.f)) / {norm}, 9) FROM e JOIN t ON t.item = e.item) AS point_err_mean"
    cols = lambda at: f"'{vary}' AS vary_name, {at.value!r}::DOUBLE AS vary_value, {_ERRORS}, {every.format(norm=dbl(norm_of(at.stream())))}"
    return " UNION ALL ".join(f"({measured_sql(at.stream(), at.params(), at.shards, at.phi, cols(at), at.total_sql)})" for at in wl.points(vary, _COPIES))


for _v in wl.SWEEPS:
    query(f"faded_hh_metrics_{_v}", sweep_sql(_v))(lambda spark, sf_dir, v=_v: wl.accuracy(spark, sf_dir, v).drop("are", "abs_err_max", "abs_err_mean"))
    query(f"faded_hh_errors_{_v}", error_sql(_v))(lambda spark, sf_dir, v=_v: rounded(wl.accuracy(spark, sf_dir, v, _COPIES, folded=True)).select("vary_name", "vary_value", "are", "abs_err_max", "abs_err_mean", F.round("point_err_mean", 9).alias("point_err_mean")))

_TINY = (2, 8, 32, 128, 800)


def folded_answer(spark, sf_dir, phi: float, w: int, p: int = 4) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(answer, truth, all exact frequencies) of a folded sketch of any size, all normalised."""
    m = folded_users(spark, sf_dir, w=w, p=p)
    true = exact.decayed_frequency(USERS.weighted(spark, sf_dir)).withColumn("f", F.col("f") / F.lit(norm_of(USERS)))
    return m.heavy_hitters(phi, wl.EVENTS_TO, strict=False), metrics.truth(true, phi), true


@query("tiny_sketch_recall", " UNION ALL ".join(f"({measured_sql(USERS, USERS.params(w=w), 4, PHI['users'], f'{w} AS w, {_RATIOS}, round(are, 9) AS are')})" for w in _TINY))
def _tiny(spark, sf_dir):
    """Recall of ever smaller sketches: it holds at 800 columns and falls only for extremely small ones."""
    out = None
    for w in _TINY:
        got, _, true = folded_answer(spark, sf_dir, PHI["users"], w)
        row = rounded(metrics.summary(got, true, PHI["users"])).select(F.lit(w).alias("w"), "truth", "reported", "hits", "precision", "recall", "are")
        out = row if out is None else out.union(row)
    return out


@query("tolerance_contract", f"WITH f AS (SELECT item, sum(x) AS f FROM ({_Z.weighted_sql()}) GROUP BY item), c AS (SELECT sum(f) AS c FROM f) SELECT count(*) AS truth, 0::BIGINT AS missed, 0::BIGINT AS intruders FROM f, c WHERE f > 0.01::DOUBLE * c")
def _tolerance(spark, sf_dir):
    weighted, p = _Z.weighted(spark, sf_dir), _Z.params(w=1340)
    return invariants.tolerance_contract(miner.mine_weighted(weighted, p).heavy_hitters(0.01, _Z.now), weighted, 0.01, p.eps)


_BOUND_POINTS = [(d, seed) for d in (1, 2, 4) for seed in (1, 2, 3)]


def _bound_sql(d: int, seed: int) -> str:
    p = USERS.params(w=128, d=d, seed=seed)
    return f"""({estimate_sql(USERS, p, 4)}, t AS (SELECT item, sum(x) AS f FROM ({USERS.weighted_sql()}) GROUP BY item), c AS (SELECT sum(f) AS c FROM t)
    SELECT {d} AS d, {seed} AS seed, count(*) FILTER (WHERE f > {dbl(PHI['users'])} * c) AS truth, count(*) FILTER (WHERE f > {dbl(PHI['users'])} * c AND t.item NOT IN (SELECT cell[1].i FROM m)) AS missed,
    {dbl(sizing.miss_bound(PHI['users'], d, 128))} AS miss_bound, count(*) AS items, count(*) FILTER (WHERE est - f >= {dbl(p.eps)} * c) AS violations, count(*) FILTER (WHERE est - f >= {dbl(p.eps)} * c) / count(*) AS rate, {dbl(sizing.implied(d, 128)[1])} AS delta
    FROM t CROSS JOIN c JOIN e ON e.item = t.item)"""


@query("bound_checks", " UNION ALL ".join(_bound_sql(d, seed) for d, seed in _BOUND_POINTS))
def _bound_checks(spark, sf_dir):
    """Both probabilistic bounds over hash seeds on small grids: misses against the detection bound and error violations
    against delta."""
    weighted = sketch.block_shards(USERS.weighted(spark, sf_dir), 4, event_rows(spark, sf_dir))
    true = exact.decayed_frequency(weighted)
    heavy = metrics.truth(true, PHI["users"])
    out = None
    for d, seed in _BOUND_POINTS:
        p = USERS.params(w=128, d=d, seed=seed)
        cells = miner.mine_folded(weighted, p, 4).cells
        miss = metrics.missed_candidates(cells, heavy)
        bad = metrics.bound_violations(sketch.raw_estimates(cells, p, true.select("item")), true, p.eps)
        row = miss.crossJoin(bad).select(F.lit(d).alias("d"), F.lit(seed).alias("seed"), "truth", "missed", F.lit(sizing.miss_bound(PHI["users"], d, 128)).alias("miss_bound"), "items", "violations", "rate", F.lit(sizing.implied(d, 128)[1]).alias("delta"))
        out = row if out is None else out.union(row)
    return out


@query("local_cells_emitted", f"SELECT shard, count(*) AS cells, count(*) * {measure.CELL_BYTES} AS bytes FROM (SELECT DISTINCT ord * 4 // {_EVENT_ROWS} AS shard, row, col FROM ({rows_sql(f'SELECT * FROM ({USERS.weighted_sql()})', USERS.params(), ', ord')})) GROUP BY shard")
def _emitted(spark, sf_dir):
    """Cost of the reduction: cells that each local sketch hands on, and their bytes."""
    weighted = sketch.block_shards(USERS.weighted(spark, sf_dir), 4, event_rows(spark, sf_dir))
    return measure.cells_emitted(sketch.local_sketches(weighted, USERS.params()))


# ---- k-counter summaries and related algorithms ----


def _summary(spark, sf_dir, k: int, p: int) -> DataFrame:
    s = USERS.weighted(spark, sf_dir)
    s = sketch.block_shards(s, p, event_rows(spark, sf_dir)) if p > 1 else s.withColumn("shard", F.lit(0))
    return spacesaving.merge(spacesaving.fold_stream(s, k), k)


def summary_sql(k: int, p: int) -> str:
    shard = f"(ord * {p} // (SELECT max(event_id) + 1 FROM events))" if p > 1 else "0"
    merge = cell.merge_sql("a", "b", k)
    return f"""WITH l AS (SELECT shard, list_reduce(list([{{'n': -x, 'i': item}}] ORDER BY ord), lambda a, b: {merge}) AS cell FROM (SELECT *, {shard} AS shard FROM ({USERS.weighted_sql()})) GROUP BY shard),
    m AS (SELECT list_reduce(list(cell ORDER BY shard), lambda a, b: {merge}) AS cell FROM l)"""


for _n, _p in (("spacesaving_k8", 1), ("spacesaving_merge_k8", 4)):
    query(_n, f"{summary_sql(8, _p)} SELECT c.i AS item, -c.n AS est FROM (SELECT unnest(cell) AS c FROM m)")(lambda spark, sf_dir, p=_p: spacesaving.to_rows(_summary(spark, sf_dir, 8, p)))

query("spacesaving_norm_deficit", " UNION ALL ".join(f"(SELECT {k} AS k, mass, norm, mass - norm AS deficit FROM ({summary_sql(k, 4)} SELECT (SELECT sum(x) FROM ({USERS.weighted_sql()})) AS mass, -list_sum(list_transform(cell, lambda c: c.n)) AS norm FROM m))" for k in (2, 3, 8)))(
    lambda spark, sf_dir: _deficits(spark, sf_dir)
)


def _deficits(spark, sf_dir):
    mass = sketch.global_count(USERS.weighted(spark, sf_dir)).withColumnRenamed("c", "mass")
    out = None
    for k in (2, 3, 8):
        row = spacesaving.norm_deficit(_summary(spark, sf_dir, k, 4), mass).select(F.lit(k).alias("k"), "mass", "norm", "deficit")
        out = row if out is None else out.union(row)
    return out




def _plain(spark, sf_dir):
    z = wl.zipf(1.4)
    return z.build(spark, sf_dir)


_ZP = wl.zipf(1.4)
_ZN = f"(SELECT item, count(*) AS f FROM ({_ZP.sql}) GROUP BY item)"


def _guarantee(found: DataFrame, stream: DataFrame, need: float, slack: float) -> DataFrame:
    """(truth, missed, over, under): items that must be found, those not found, and bounds broken by ``low``."""
    true = stream.groupBy("item").agg(F.count("*").alias("f"))
    n = true.agg(F.sum("f").alias("n"))
    both = true.join(found.select("item", "low"), "item", "left").crossJoin(F.broadcast(n))
    must = F.col("f") > F.lit(need) * F.col("n")
    return both.agg(F.count_if(must).alias("truth"), F.count_if(must & F.col("low").isNull()).alias("missed"), F.count_if(F.col("low") > F.col("f")).alias("over"), F.count_if(F.col("low") < F.col("f") - F.lit(slack) * F.col("n")).alias("under"))


_GUARANTEE = f"SELECT count(*) FILTER (WHERE f > {{need}}::DOUBLE * n) AS truth, 0::BIGINT AS missed, 0::BIGINT AS over, 0::BIGINT AS under FROM {_ZN}, (SELECT sum(f) AS n FROM {_ZN})"


@query("frequent_items_k", _GUARANTEE.format(need=1 / 101))
def _frequent(spark, sf_dir):
    s = _plain(spark, sf_dir)
    return _guarantee(related.frequent(s, 100), s, 1 / 101, 1 / 101)


@query("lossy_counting_eps", _GUARANTEE.format(need=0.005))
def _lossy(spark, sf_dir):
    s = _plain(spark, sf_dir)
    return _guarantee(related.lossy_counting(s, 0.005), s, 0.005, 0.005)


@query("sticky_sampling", _GUARANTEE.format(need=0.02))
def _sticky(spark, sf_dir):
    s = _plain(spark, sf_dir)
    n = event_rows(spark, sf_dir) * 6
    return _guarantee(related.sticky_sampling(s, 0.02, 0.01, 0.001, n).withColumnRenamed("count", "low"), s, 0.02, 0.01)


@query("spacesaving_hh", _GUARANTEE.format(need=0.01))
def _ss(spark, sf_dir):
    """k counters over-estimate by at most n / k; lowered by that, they never exceed the truth."""
    s = _plain(spark, sf_dir).withColumn("x", F.lit(1.0))
    parts = spacesaving.build(s, 400)
    mass = parts.agg(F.sum("mass").alias("mass"))
    low = spacesaving.to_rows(spacesaving.merge(parts, 400)).crossJoin(F.broadcast(mass)).select("item", F.greatest(F.col("est") - F.col("mass") / 400, F.lit(0.0)).alias("low"))
    return _guarantee(low, s, 0.01, 1 / 400)


_CS = _Z.params(w=1360, d=5)


@query("count_sketch_est", f"""WITH s AS ({_Z.weighted_sql()}), h AS ({' UNION ALL '.join(f"SELECT {r} AS row, {h} AS col, {g} * 2 - 1 AS sign, item, x FROM s" for r, (h, g) in enumerate(zip(_CS.hashes.sql(), related.signs(_CS).sql())))}),
k AS (SELECT row, col, sum(sign * x) AS f FROM h GROUP BY row, col), e AS (SELECT item, median(sign * k.f) AS est FROM (SELECT DISTINCT item, row, col, sign FROM h) p JOIN k ON k.row = p.row AND k.col = p.col GROUP BY item)
SELECT item, f, est FROM e JOIN (SELECT item, sum(x) AS f FROM s GROUP BY item) USING (item)""")
def _count_sketch(spark, sf_dir):
    """Estimates of all items beside their exact frequencies."""
    s = _Z.weighted(spark, sf_dir)
    true = exact.decayed_frequency(s)
    return related.count_sketch_estimate(related.count_sketch(s, _CS), _CS, true).join(true, "item").select("item", "f", "est")


@query("group_test_hh", hh_sql(_Z, 0.05, "item"))
def _group_test(spark, sf_dir):
    s, p = _Z.weighted(spark, sf_dir), _Z.params(w=1360)
    got = related.group_test(s, p, 0.05, bits=16)
    return sketch.verify(got, s, p, 0.05, _Z.now).select("item")


_HC = _Z.params(w=1360).with_(seed=1001)


@query("hcount_est", f"""WITH s AS ({_Z.weighted_sql()}), h AS ({rows_sql('SELECT * FROM s', _HC)}), k AS (SELECT row, col, sum(x) AS f FROM h GROUP BY row, col)
SELECT item, f, est FROM (SELECT item, min(k.f) AS est FROM (SELECT DISTINCT item, row, col FROM h) p JOIN k ON k.row = p.row AND k.col = p.col GROUP BY item) JOIN (SELECT item, sum(x) AS f FROM s GROUP BY item) USING (item)""")
def _hcount(spark, sf_dir):
    """Estimates of all items beside their exact frequencies."""
    s, p = _Z.weighted(spark, sf_dir), _Z.params(w=1360)
    true = exact.decayed_frequency(s)
    return related.hcount_estimate(related.hcount(s, p), _HC, true).join(true, "item").select("item", "f", "est")


@query("builtin_top_k", f"SELECT item, f AS n FROM {_ZN} ORDER BY f DESC, item LIMIT 10")
def _builtin(spark, sf_dir):
    return related.builtin_top_k(_plain(spark, sf_dir), 10)


@query("builtin_count_min_size", "SELECT 1::BIGINT AS sketches, true AS bounded")
def _builtin_count_min(spark, sf_dir):
    """The engine's own Count-Min yields one sketch whose size depends on its bounds only; its cells cannot be read in SQL."""
    size = F.octet_length("sketch")
    return related.builtin_count_min(_plain(spark, sf_dir), 0.01, 0.95).agg(F.count("*").alias("sketches"), (F.max(size) < 64_000).alias("bounded"))


@query("approx_vs_exact_distinct", f"SELECT count(DISTINCT item) AS exact, true AS within FROM ({PARTS.weighted_sql()})")
def _distinct(spark, sf_dir):
    """The approximate count lies within three of its standard deviations (5 %)."""
    n, guess = F.countDistinct("item"), F.approx_count_distinct("item", 0.05)
    return PARTS.weighted(spark, sf_dir).agg(n.alias("exact"), (F.abs(guess - n) <= F.greatest(0.15 * n, F.lit(1.0))).alias("within"))


# ---- joins and set operations around answers ----

_ERR = 30 * 60 * 1_000_000


@query("near_error_users", f"""WITH h AS ({hh_sql(USERS, 0.0122, 'item')}), e AS (SELECT event_id, user_id AS item, epoch_us(ts) AS tick, event_type FROM events WHERE epoch_us(ts) > {wl.EVENTS_FROM}::BIGINT AND epoch_us(ts) <= {wl.EVENTS_TO}::BIGINT AND user_id IN (SELECT item FROM h))
SELECT a.item, count(DISTINCT a.event_id) AS n FROM e a JOIN e b ON a.item = b.item AND b.event_type = 'error' AND a.tick BETWEEN b.tick - {_ERR}::BIGINT AND b.tick + {_ERR}::BIGINT GROUP BY a.item""")
def _near(spark, sf_dir):
    return wl.near_errors(spark, sf_dir, exact.heavy_hitters(USERS.weighted(spark, sf_dir), 0.0122), _ERR)


@query("verify_semi", hh_sql(PARTS, 0.0016, "item, f / {norm} AS f"))
def _verify(spark, sf_dir):
    s = PARTS.weighted(spark, sf_dir)
    every = countmin.heavy_hitters(s, _CMH, 0.0012)
    return sketch.verify(every, s, _CMH, 0.0016, PARTS.now)


_W2 = USERS.params(w=2)
_SMALLEST = f"""{estimate_sql(USERS, _W2, 4)}, t AS (SELECT item, sum(x) AS f FROM ({USERS.weighted_sql()}) GROUP BY item), c AS (SELECT sum(f) AS c FROM t),
a AS (SELECT item FROM e, c WHERE est > {dbl(0.0122)} * c AND item IN (SELECT cell[1].i FROM m, c WHERE -cell[1].n > {dbl(0.0122)} * c))"""


@query("misses_anti", f"{_SMALLEST} SELECT item, f / {dbl(norm_of(USERS))} AS f FROM t, c WHERE f > {dbl(0.0122)} * c AND item NOT IN (SELECT item FROM a)")
def _misses(spark, sf_dir):
    """True heavy hitters that a sketch of two columns loses."""
    answer, true, _ = folded_answer(spark, sf_dir, 0.0122, 2)
    return metrics.misses(answer, true)


@query("answer_setops", f"SELECT 'both' AS part, item FROM ({hh_sql(PARTS, 0.0016, 'item')})")
def _setops(spark, sf_dir):
    s = PARTS.weighted(spark, sf_dir)
    true = metrics.truth(exact.decayed_frequency(s), 0.0016)
    return metrics.set_ops(miner.mine_weighted(s, PARTS.params()).heavy_hitters(0.0016, PARTS.now), true)


@query("outside_guarantee_metrics", measured_sql(USERS, USERS.params(w=16), 4, 0.0122, f"{_RATIOS}, {_ERRORS}"))
def _outside(spark, sf_dir):
    """What leaving the guarantee costs: intruders, misses and larger errors."""
    answer, _, true = folded_answer(spark, sf_dir, 0.0122, 16)
    return rounded(metrics.summary(answer, true, 0.0122))


@query("asof_snapshot_pick", """WITH s AS (SELECT user_id % 4 AS site, event_id AS snapshot, value AS lcount FROM events), q AS (SELECT max(event_id) AS at_ FROM events GROUP BY date_trunc('day', ts))
SELECT at_ AS as_of, site, max(snapshot) AS snapshot, arg_max(lcount, snapshot) AS lcount FROM s, q WHERE snapshot <= at_ GROUP BY at_, site""")
def _asof(spark, sf_dir):
    """Every event a snapshot of one of four sites; per day's end the newest one of each site, in one pass."""
    from fadedhh.sources.sketch_io import newest_at

    e = load(spark, sf_dir, "events")
    meta = e.select(F.expr("user_id % 4").alias("site"), F.col("event_id").alias("snapshot"), F.col("value").alias("lcount"))
    return newest_at(meta, e.groupBy(F.date_trunc("day", "ts")).agg(F.max("event_id").alias("as_of")).select("as_of"))


@query("zipf_rank_counts", f"SELECT item, count(*) AS n FROM ({_Z.sql}) GROUP BY item")
def _zipf_ranks(spark, sf_dir):
    return _Z.build(spark, sf_dir).groupBy("item").agg(F.count("*").alias("n"))


# ---- SQL surface and streams ----


@query("sql_surface_hh", _FADED_USERS)
def _surface(spark, sf_dir):
    """The same answer through the SQL functions and the table function."""
    sqlapi.register(spark)
    m = folded_users(spark, sf_dir, w=256, p=4)
    m.cells.createOrReplaceTempView("faded_cells")
    c = m.count.first()["c"]
    return spark.sql(f"SELECT item, est FROM faded_hh(TABLE(SELECT row, col, i1, f1, i2, f2 FROM faded_cells) WITH SINGLE PARTITION, {c!r}D, 0.0122D, {norm_of(USERS)!r}D, 4, 256, 1)")


@query("sql_weight_function", f"SELECT event_id, pow(2.0::DOUBLE, {_AGE} // {wl.DAY}::BIGINT) AS w FROM {_EV}")
def _sql_weight(spark, sf_dir):
    sqlapi.register(spark)
    call = sqlapi.weight_sql(DecaySpec.dyadic(wl.DAY)).replace("landmark", f"{wl.EVENTS_FROM}L")
    return _timed(spark, sf_dir).select("event_id", F.expr(call).alias("w"))


query("online_hh_final", _FADED_USERS)(lambda spark, sf_dir: online_runs.final_answer(spark, sf_dir, _W256, 4, 0.0122))
query("online_window_counts", "SELECT date_trunc('day', ts) AS start, date_trunc('day', ts) + INTERVAL 1 DAY AS \"end\", event_type, count(*) AS n FROM events GROUP BY ALL")(online_runs.window_counts)
query("online_session", """WITH e AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts) IS NULL THEN 1 ELSE 0 END AS fresh FROM events),
g AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e)
SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 6 HOUR AS "end", count(*) AS n FROM g GROUP BY user_id, k""")(online_runs.session_counts)
