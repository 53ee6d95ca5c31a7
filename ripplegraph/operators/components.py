"""Connected components by alternating star contraction; the driver sees two numbers a round."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ripplegraph.plans.scratch import BROADCAST_ROWS, Scratch

#: A task of these rounds gets so many edges; small graphs do not pay for empty tasks.
ROWS_PER_TASK = 100_000
FEWEST_TASKS = 4


def components(spark: SparkSession, edges: DataFrame, scratch: Scratch | None = None, max_rounds: int = 60) -> DataFrame:
    """(id, component) of every node of ``edges(src, dst)``: the smallest id it can reach.

    ``edges`` should be a written table, as it is counted first. Each round hangs every node below the smallest
    node next to it, first from the larger side, then from the smaller, and ends the loop once each node is a
    root or the child of one root. A round shuffles the edges only and minima are combined before the shuffle.
    There are at most twice as many minima as edges: within the bound they are broadcast, beyond it the joins
    read written tables on both sides, so a hub is split over tasks. Self-loops give one-node components.
    """
    scratch = scratch or Scratch(spark, "components")
    n_edges = edges.count()
    save = lambda df: scratch.save(df.coalesce(max(FEWEST_TASKS, -(-n_edges // ROWS_PER_TASK))))
    minima = F.broadcast if 2 * n_edges <= BROADCAST_ROWS else save
    known = save(edges.where("src is not null and dst is not null").select(F.greatest("src", "dst").alias("u"), F.least("src", "dst").alias("v")).distinct())
    cur = known.where("u <> v")
    for _ in range(max_rounds):
        both = cur.unionByName(cur.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = minima(both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m")))
        large = save(both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct())
        low = minima(large.groupBy("u").agg(F.min("v").alias("m")))
        cur = save(large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(low.select("u", F.col("m").alias("v"))).distinct())
        ends = cur.select("u", F.lit(1).alias("below"), F.lit(0).alias("above")).unionByName(cur.select(F.col("v").alias("u"), F.lit(0).alias("below"), F.lit(1).alias("above")))
        if not ends.groupBy("u").agg(F.sum("below").alias("below"), F.max("above").alias("above")).where("below > 1 or below + above > 1").agg(F.count("*")).first()[0]:
            break
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    leaves = cur.select(F.col("u").alias("id"), F.col("v").alias("component"))
    roots = cur.select(F.col("v").alias("id"), F.col("v").alias("component")).distinct()
    loops = known.where("u = v").select(F.col("u").alias("id")).join(leaves.unionByName(roots).select("id"), "id", "left_anti").distinct()
    return save(leaves.unionByName(roots).unionByName(loops.select("id", F.col("id").alias("component"))))
