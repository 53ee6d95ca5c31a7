"""Mixing sources to target weights: repetition rates per source, then whole copies plus one random one.

The size of a document is its number of words. Sources, ordered by code point with null last, weigh
5, 2, 1, repeating. Together they get 150% of all words by weight; no target exceeds twice its source's
size, and what is above is shared again by weight. This has a closed form: order the sources by
cap / weight; the first one whose share of what its predecessors leave fits under its cap sets the level
for it and all after it, and those before it get their caps.

Each document is emitted floor(rate) times, and once more with the probability of the fraction, drawn
from a hash of the seed and its id (its text where the id is null). So reruns agree, and rows with equal
ids share a draw. Null and empty texts have size 0 and are emitted like others of their source; a source
without words has rate 0. Extra columns stay. Native SQL; the only rows gathered are one per source.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ripplegraph.llm.store import Scratch, bounded_broadcast, table, text_of

WEIGHTS = (5, 2, 1)
BUDGET = 1.5
MOST = 2
SEED = "mix-1"


def size_of(text: str = "text") -> Column:
    return F.regexp_count(text_of(text), F.lit(r"[^\x20\x09-\x0D]+")).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, budget: float = BUDGET, most: int = MOST) -> DataFrame:
    """(source, source_size, target) from (source, source_size), one row per source."""
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    weight = F.element_at(F.array(*(F.lit(w) for w in weights)), (F.pmod(F.row_number().over(by_name) - 1, F.lit(len(weights))) + 1).cast("int"))
    sized = sizes.withColumn("weight", weight.cast("double")).withColumn("cap", F.col("source_size").cast("double") * most)
    by_ratio = Window.orderBy(F.col("cap") / F.col("weight"), F.col("source").asc_nulls_last())
    everything = Window.partitionBy()
    before = F.coalesce(F.sum("cap").over(by_ratio.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    rest = F.sum("weight").over(by_ratio.rowsBetween(0, Window.unboundedFollowing))
    total = F.sum("source_size").over(everything).cast("double") * budget
    placed = sized.withColumn("place", F.row_number().over(by_ratio)).withColumn("share", (total - before) / rest)
    level = F.min_by("share", F.when(F.col("share") * F.col("weight") <= F.col("cap"), F.col("place"))).over(everything)
    return placed.withColumn("level", level).select("source", "source_size", F.least("cap", F.col("level") * F.col("weight")).alias("target"))


def draw(seed: str = SEED) -> Column:
    """A number in [0, 1) from the seed and the document's id."""
    key = F.coalesce(F.col("doc_id").cast("string"), F.md5(text_of("text")))
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), key)), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def mix(spark: SparkSession, docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, budget: float = BUDGET, most: int = MOST, seed: str = SEED) -> DataFrame:
    """``docs`` with the columns mix_size, mix_source_size, mix_target, mix_rate and mix_copies."""
    scratch = Scratch(spark, "op10")
    sizes = docs.select("source", size_of().alias("size")).groupBy("source").agg(F.sum("size").alias("source_size"))
    targets = scratch.save(source_targets(sizes, weights, budget, most), "targets").toDF("mix_source", "mix_source_size", "mix_target")
    rated = docs.join(bounded_broadcast(targets, targets.count()), docs["source"].eqNullSafe(targets["mix_source"])).drop("mix_source")
    rate = F.when(F.col("mix_source_size") > 0, F.col("mix_target") / F.col("mix_source_size")).otherwise(F.lit(0.0))
    rated = rated.withColumn("mix_size", size_of()).withColumn("mix_rate", rate)
    whole = F.floor("mix_rate")
    return rated.withColumn("mix_copies", (whole + F.when(draw(seed) < F.col("mix_rate") - whole, 1).otherwise(0)).cast("int"))


def emit(mixed: DataFrame) -> DataFrame:
    """Each document as often as the mix takes it; ``mix_copy`` counts from 1."""
    return mixed.where("mix_copies > 0").withColumn("mix_copy", F.explode(F.sequence(F.lit(1), F.col("mix_copies"))))


def op10_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mix(spark, table(spark, sf_dir, "documents").select("doc_id", "text", "source"))
    return mixed.select("doc_id", F.col("mix_size").alias("size"), F.col("mix_source_size").alias("source_size"), F.col("mix_target").alias("target"), (F.col("mix_size") * F.col("mix_copies")).alias("taken"))


ORACLE = r"""
WITH d AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
    ('0x' || substr(md5('mix-1:' || coalesce(CAST(doc_id AS VARCHAR), md5(coalesce(text, '')))), 1, 8))::BIGINT::DOUBLE / 4294967296.0 AS u
  FROM documents
), s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
w AS (SELECT *, [5.0, 2.0, 1.0][(row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1]::DOUBLE AS weight, 2.0::DOUBLE * source_size AS cap FROM s),
p AS (
  SELECT *, row_number() OVER o AS place,
    (1.5::DOUBLE * (SELECT sum(source_size) FROM s)::DOUBLE - coalesce(sum(cap) OVER (ORDER BY cap / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0))
    / sum(weight) OVER (ORDER BY cap / weight, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS share
  FROM w WINDOW o AS (ORDER BY cap / weight, source NULLS LAST)
), t AS (
  SELECT source, source_size, least(cap, (SELECT arg_min(share, place) FROM p WHERE share * weight <= cap) * weight) AS target FROM p
), r AS (SELECT d.*, t.source_size, t.target, CASE WHEN t.source_size > 0 THEN t.target / t.source_size ELSE 0.0 END AS rate FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, source_size, target, (size * (floor(rate)::BIGINT + CASE WHEN u < rate - floor(rate) THEN 1 ELSE 0 END))::BIGINT AS taken FROM r
"""
