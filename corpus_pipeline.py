"""From raw documents to a training mix: five stages, each over all that its predecessor kept.

Every stage takes (spark, docs, sf_dir) and returns a frame; each result is written as Parquet and read again
as the next stage's input. Null columns, empty and very long texts, repeated rows, empty tables and extra
columns pass through as the operators define it. Columns that begin with ``mix_`` are set by the last stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ripplegraph.llm import op5_ngram_join, op6_decontamination, op7_toxicity, op8_pii, op10_mixing
from ripplegraph.llm.store import Scratch, bounded_broadcast, fresh, table, text_of


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents predicted toxic go."""
    return op7_toxicity.without_toxic(docs, table(spark, sf_dir, "labels"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of linked ones stays: the one with the smallest id."""
    return op5_ngram_join.one_of_each(spark, docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that leak a benchmark item go."""
    scratch = Scratch(spark, "decontamination")
    found = op6_decontamination.leaks(spark, docs, table(spark, sf_dir, "benchmark"), scratch)
    own, of, text = fresh(docs, "own_hash", "gone_id", "gone_hash")
    gone = scratch.save(found.select(F.col("doc_id").alias(of), F.col("th").alias(text)).distinct(), "gone")
    rows = docs.withColumn(own, F.xxhash64(text_of("text")))
    same = rows["doc_id"].cast("long").eqNullSafe(gone[of]) & (rows[own] == gone[text])
    return rows.join(bounded_broadcast(gone, gone.count()), same, "left_anti").select(*docs.columns)


def pii(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data become pseudonyms; n_chars follows the text."""
    changed = op8_pii.pseudonymise(docs, count=None)
    return changed.withColumn("n_chars", F.coalesce(F.length("text").cast("long"), F.col("n_chars"))) if "n_chars" in docs.columns else changed


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as its source's rate asks; ``mix_copy`` tells the copies apart."""
    return op10_mixing.emit(op10_mixing.mix(spark, docs)).select(*docs.columns, "mix_copy")


STAGES = [
    ("toxicity", toxicity),
    ("near_duplicates", near_duplicates),
    ("decontamination", decontamination),
    ("pii", pii),
    ("mixing", mixing),
]

#: Scores, groups and keyed pseudonyms have no SQL form: tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark, "pipeline")
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = scratch.save(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
