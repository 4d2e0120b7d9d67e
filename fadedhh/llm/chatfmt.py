"""Chat formatting: collapse cumulative snapshots of conversations, then render the rest.

A chat service that logs a conversation after every turn stores each conversation many times over.
A rolling hash of the turns names every prefix of every conversation; a conversation whose whole hash
is a proper prefix of another one goes (anti-join), and of equal conversations the smallest id stays.

Only DataFrame functions. Texts are not shuffled for the comparison: just (id, place, hash) rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

_HALF = 0xFFFFFFFF


def _halves(h: Column, name: str) -> list[Column]:
    return [h.bitwiseAND(F.lit(_HALF)).alias(f"{name}_lo"), F.shiftrightunsigned(h, 32).alias(f"{name}_hi")]


def prefix_hashes(turns: DataFrame) -> DataFrame:
    """(conv_id, n, total, h): for each conversation the hash of its first n turns.

    Place and content of each turn hash to 128 bits; a prefix is the sum of its turns' hashes, kept in
    32-bit halves so that sums stay exact. Turns order by number, null first; turns of one number by the hashes of role
    and text, so that no text is shuffled here. A null role or text counts as a value of its own.
    """
    order = W.partitionBy("conv_id").orderBy("turn", "rh", "th")
    slim = turns.select(
        "conv_id", "turn",
        F.xxhash64(F.col("role"), F.col("role").isNull()).alias("rh"),
        F.xxhash64(F.col("text"), F.col("text").isNull()).alias("th"),
        F.hash("text", "role").cast("long").alias("tk"),
    )
    placed = slim.withColumn("n", F.row_number().over(order).cast("long"))
    parts = placed.select(
        "conv_id", "n", "turn", "rh", "th",
        *_halves(F.xxhash64(F.lit(17), "n", "rh", "th", "tk"), "a"), *_halves(F.xxhash64(F.lit(91), "tk", "th", "rh", "n"), "b"),
    )
    run = W.partitionBy("conv_id").orderBy("turn", "rh", "th").rowsBetween(W.unboundedPreceding, 0)
    whole = W.partitionBy("conv_id")
    return parts.select(
        "conv_id", "n", F.count("*").over(whole).alias("total"),
        F.struct(*[F.sum(c).over(run).alias(c) for c in ("a_lo", "a_hi", "b_lo", "b_hi")]).alias("h"),
    )


def maximal_conversations(turns: DataFrame) -> DataFrame:
    """conv_ids that no longer conversation extends; the smallest id of equal ones."""
    hashes = prefix_hashes(turns)
    inner = hashes.where("n < total").select("n", "h").distinct()
    whole = hashes.where("n = total").groupBy("n", "h").agg(F.min("conv_id").alias("conv_id"))
    return whole.join(inner, ["n", "h"], "left_anti").select("conv_id")


def render(turns: DataFrame) -> DataFrame:
    """(conv_id, n_turns, text): each turn as ``<|role|>``, newline, text, ``<|end|>``; joined by newlines.
    A null role renders as ``user`` and a null text as empty."""
    one = F.concat(F.lit("<|"), F.coalesce("role", F.lit("user")), F.lit("|>\n"), F.coalesce("text", F.lit("")), F.lit("<|end|>"))
    rows = turns.select("conv_id", F.struct(F.col("turn"), F.xxhash64(F.col("role"), F.col("role").isNull()).alias("rh"), F.xxhash64(F.col("text"), F.col("text").isNull()).alias("th"), one.alias("s")).alias("x"))
    lists = rows.groupBy("conv_id").agg(F.sort_array(F.collect_list("x")).alias("xs"))
    return lists.select("conv_id", F.size("xs").cast("long").alias("n_turns"), F.concat_ws("\n", F.transform("xs", lambda x: x["s"])).alias("text"))


def chat_format(conversations: DataFrame) -> DataFrame:
    """Rendered maximal conversations. Rows without conv_id go; an empty table gives an empty result;
    repeated turns count as turns; columns beyond conv_id, turn, role, text are ignored.

    One conversation becomes one text, so it must fit a row; nothing else is gathered per key.
    """
    turns = conversations.select("conv_id", F.col("turn").cast("long").alias("turn"), "role", "text").where("conv_id is not null")
    kept = maximal_conversations(turns)
    return render(turns.join(kept, "conv_id", "left_semi"))


def chat_query(conversations: DataFrame) -> DataFrame:
    """Digests of the rendered conversations; nulls, repeats and empty tables as in ``chat_format``."""
    out = chat_format(conversations)
    return out.select("conv_id", "n_turns", F.length("text").cast("long").alias("n_chars"), F.sha2("text", 256).alias("text_sha256"))


#: Equal where the turns of a conversation have different numbers.
ORACLE = """
WITH t AS (SELECT conv_id, turn, coalesce(role, 'user') AS role, coalesce(text, '') AS text FROM conversations WHERE conv_id IS NOT NULL),
c AS (SELECT conv_id, list('<|' || role || '|>' || chr(10) || text || '<|end|>' ORDER BY turn, role, text) AS xs FROM t GROUP BY conv_id),
p AS (SELECT DISTINCT unnest(list_transform(range(1, len(xs)), lambda n: array_to_string(xs[1:n], chr(10)))) AS s FROM c),
w AS (SELECT min(conv_id) AS conv_id, len(any_value(xs)) AS n_turns, array_to_string(xs, chr(10)) AS s FROM c GROUP BY xs)
SELECT conv_id, n_turns::BIGINT AS n_turns, length(s)::BIGINT AS n_chars, sha256(s) AS text_sha256
FROM w WHERE NOT EXISTS (SELECT 1 FROM p WHERE p.s = w.s)
"""
