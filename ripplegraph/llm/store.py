"""Helpers for text columns and tables of unknown quality."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ripplegraph.plans.scratch import BROADCAST_ROWS, Scratch, bounded_broadcast

__all__ = ["BROADCAST_ROWS", "SEPARATORS", "Scratch", "ascii_lower", "bounded_broadcast", "fresh", "keyed", "same_row", "table", "text_of", "words_of"]

#: One or more of the six ASCII separators; everything else belongs to a word.
SEPARATORS = r"[\x20\x09-\x0D]+"


def text_of(column: str | Column) -> Column:
    """A null text is an empty one."""
    return F.coalesce(F.col(column) if isinstance(column, str) else column, F.lit(""))


def ascii_lower(column: Column) -> Column:
    """Lower-case A to Z and nothing else."""
    return F.translate(column, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def words_of(column: str | Column) -> Column:
    """Array of the words of a text; empty for null and empty texts."""
    return F.filter(F.split(text_of(column), SEPARATORS), lambda w: w != "")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def keyed(docs: DataFrame) -> DataFrame:
    """(doc_id, text, th): rows are known by their id and a hash of their text, as ids may repeat or be null."""
    return docs.select(F.col("doc_id").cast("long"), text_of("text").alias("text")).withColumn("th", F.xxhash64("text"))


def same_row(left: DataFrame, right: DataFrame) -> Column:
    return left["doc_id"].eqNullSafe(right["doc_id"]) & (left["th"] == right["th"])


def fresh(docs: DataFrame, *names: str) -> list[str]:
    """``names``, each with as many underscores before it as no column of ``docs`` has (whatever the case)."""
    have = {c.lower() for c in docs.columns}
    out = []
    for name in names:
        while name.lower() in have:
            name = f"_{name}"
        out.append(name)
    return out
