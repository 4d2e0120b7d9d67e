"""Corpus pipeline over ``documents``: five of the training-data operators, one after the other.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame that is written and read again as the next
stage's input. All but the last return the columns of ``documents``; n_chars follows the text. Every stage takes nulls in any
column, repeated rows, texts of any length and empty tables (which stay empty).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fadedhh.llm import decontam, linededup, mixing, neardup, quality
from fadedhh.llm.common import fresh, settle, table


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rule ensemble rejects go. It learns from the labelled rows that are not held out. A null text is
    judged as an empty one; repeated rows and rows without id are judged each on their own."""
    labels = table(spark, sf_dir, "labels")
    model = quality.fit(docs.select("doc_id", "text"), labels.where(~quality.held_out()))
    f = fresh(docs, "_qc_")
    return quality.score(docs, model, names=(f"{f}score", f"{f}good")).where(f"{f}good = 1").select(*docs.columns)


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later copies of repeated runs of lines go; a document of which nothing but blank lines is left goes too."""
    names = [c for c in docs.columns if c.startswith("ld_")]
    if names:  # columns that the operator would replace pass under other names
        f = fresh(docs, "_kept_")
        docs_ = docs.withColumnsRenamed({c: f + c for c in names})
        return line_stage(spark, docs_, sf_dir).withColumnsRenamed({f + c: c for c in names}).select(*docs.columns)
    out = linededup.dedup_lines(docs)
    left = (F.col("ld_removed") == 0) | (F.length(F.trim(F.translate("text", "\n\r\t", ""))) > 0)
    return out.where(left).withColumn("n_chars", F.when(F.col("ld_removed") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))).select(*docs.columns)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The smallest id of each near-duplicate component stays. Rows without id are not compared and stay; rows that
    repeat an id share its fate."""
    f = fresh(docs, "_gone_")
    gone = neardup.near_duplicates(docs).where(~F.col("kept") & F.col("doc_id").isNotNull()).select(F.col("doc_id").alias(f))
    return docs.join(gone.hint("merge"), F.col("doc_id") == F.col(f), "left_anti").select(*docs.columns)


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with benchmark windows over at least a twentieth of their words go, repeated rows all alike. A null text has
    no words and stays; with an empty benchmark all stay."""
    found = decontam.verdicts(docs.select("doc_id", "text"), table(spark, sf_dir, "benchmark"))
    f = fresh(docs, "_gone_")
    gone = found.where("contaminated").select(F.col("doc_id").alias(f"{f}id"), F.col("th").alias(f"{f}th"))
    same = F.col("doc_id").eqNullSafe(F.col(f"{f}id")) & (F.xxhash64("text") == F.col(f"{f}th"))
    return docs.join(gone.hint("merge"), same, "left_anti").select(*docs.columns)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document with its place in the proportionate-fair schedule of its source. Rows without source are a source of
    their own; repeated rows are placed one by one."""
    return mixing.mix(docs)


STAGES = [
    ("quality", quality_stage),
    ("line_dedup", line_stage),
    ("near_duplicates", near_duplicate_stage),
    ("decontamination", decontamination_stage),
    ("mixing", mixing_stage),
]

#: The rule ensemble is learnt, which SQL can't express; tests hold each stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = settle(docs)
    return docs


def queries() -> dict:
    return {"pipeline": run}


def oracle_sql() -> dict[str, str]:
    return {"pipeline": ORACLE_SQL} if ORACLE_SQL else {}
