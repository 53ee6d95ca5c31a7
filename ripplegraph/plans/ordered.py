"""Places and running sums over one global order, without a window that gathers all rows in one task."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ripplegraph.plans.scratch import Scratch


def ordered(df: DataFrame, by: list[Column | str], scratch: Scratch, sums: dict[str, Column] | None = None) -> DataFrame:
    """``df`` with ``place`` from 0 in the order of ``by`` (which tells all rows apart) and running sums, each row included.

    Rows are dealt into ranges of the order and written; each range is counted within itself and moved by what
    the ranges before it hold, a table of one row per range.
    """
    sums = sums or {}
    ranged = df.withColumns({f"_{name}": x for name, x in sums.items()}).repartitionByRange(*by).withColumn("_range", F.spark_partition_id())
    ranged = scratch.save(ranged)
    within = Window.partitionBy("_range").orderBy(*by)
    totals = ranged.groupBy("_range").agg(F.count("*").alias("_n"), *(F.sum(f"_{name}").alias(f"_t_{name}") for name in sums))
    before = Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)  # one row per range
    moved = totals.select("_range", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_n"), *(F.coalesce(F.sum(f"_t_{name}").over(before), F.lit(0)).alias(f"_t_{name}") for name in sums))
    placed = ranged.withColumn("place", F.row_number().over(within) - 1).withColumns({name: F.sum(f"_{name}").over(within.rowsBetween(Window.unboundedPreceding, 0)) for name in sums})
    joined = placed.join(F.broadcast(moved), "_range")
    return joined.select(*df.columns, (F.col("place") + F.col("_n")).alias("place"), *((F.col(name) + F.col(f"_t_{name}")).alias(name) for name in sums))
