"""Joins that Spark lacks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def asof(left: DataFrame, right: DataFrame, key: str, at: str, values: list[str]) -> DataFrame:
    """``left`` with the ``values`` of the last row of ``right`` of the same ``key`` at or before ``at``; null if there is none.

    Both sides meet in one shuffle by key and one sort. Of several right rows at one time the largest struct of
    values counts. Rows of a null key, or at a null time, meet nothing.
    """
    last = right.where(F.col(key).isNotNull() & F.col(at).isNotNull()).groupBy(key, at).agg(F.max(F.struct(*values)).alias("_v"))
    rest = [c for c in left.columns if c not in (key, at)]
    mine = left.select(key, at, F.struct(*rest).alias("_l"), F.lit(1).alias("_mine"))
    both = mine.unionByName(last.select(key, at, "_v", F.lit(0).alias("_mine")), allowMissingColumns=True)
    order = Window.partitionBy(key).orderBy(F.asc_nulls_first(at), "_mine").rowsBetween(Window.unboundedPreceding, 0)
    known = F.when(F.col(key).isNotNull() & F.col(at).isNotNull(), F.last("_v", ignorenulls=True).over(order))
    met = both.withColumn("_found", known).where("_mine = 1")
    return met.select(key, at, *(F.col(f"_l.{c}").alias(c) for c in rest), *(F.col(f"_found.{c}").alias(c) for c in values))
