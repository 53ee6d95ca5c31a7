"""Search of an area by agents that spread over a belief map, with sums over clusters of agents."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ripplegraph.operators.estimation import STAGES
from ripplegraph.plans.scratch import BROADCAST_ROWS, Scratch

PI = math.pi


def basis(spark: SparkSession, kmax: int = 4, numbers: DataFrame | None = None) -> DataFrame:
    """(k1, k2, norm, lam): cosines on the unit square, their squared norms, and falling weights; of 0..kmax, or of ``numbers(id)`` up to there."""
    k = (spark.range(kmax + 1) if numbers is None else numbers.where(F.col("id").between(0, kmax)).distinct()).select(F.col("id").cast("int").alias("k1"))
    grid = k.crossJoin(F.broadcast(k.withColumnRenamed("k1", "k2")))  # (kmax + 1)**2 rows
    half = lambda c: F.when(F.col(c) == 0, 1.0).otherwise(0.5)
    return grid.select("k1", "k2", (half("k1") * half("k2")).alias("norm"), F.pow(1.0 + F.col("k1") * F.col("k1") + F.col("k2") * F.col("k2"), F.lit(-1.5)).alias("lam"))


def value(x: str = "x", y: str = "y"):
    return F.cos(F.col("k1") * PI * F.col(x)) * F.cos(F.col("k2") * PI * F.col(y))


def prior(points: DataFrame, functions: DataFrame) -> DataFrame:
    """basis with mu: mean of each cosine over the belief ``(x, y, mass)``, over its norm."""
    rows = points.join(F.broadcast(functions), F.lit(True))  # each point meets the few cosines of a fixed basis
    mu = rows.groupBy("k1", "k2", "norm", "lam").agg((F.sum(F.col("mass") * value()) / F.sum("mass")).alias("mean"))
    return mu.select("k1", "k2", "norm", "lam", (F.col("mean") / F.col("norm")).alias("mu"))


def central_sum(agents: DataFrame, functions: DataFrame) -> DataFrame:
    """(k1, k2, total): the sum of each cosine over all agents."""
    return agents.join(F.broadcast(functions), F.lit(True)).groupBy("k1", "k2").agg(F.sum(value() / F.col("norm")).alias("total"))


def clustered_sum(agents: DataFrame, functions: DataFrame) -> DataFrame:
    """The same from sums inside the agents' clusters, which are then added."""
    part = agents.join(F.broadcast(functions), F.lit(True)).groupBy("cluster", "k1", "k2").agg(F.sum(value() / F.col("norm")).alias("part"))
    return part.groupBy("k1", "k2").agg(F.sum("part").alias("total"))


def proximity(agents: DataFrame, radius: float) -> DataFrame:
    """Edges between agents within ``radius``, through grid cells."""
    cell = lambda c: F.floor(F.col(c) / radius)
    own = agents.select("id", "x", "y", cell("x").alias("cx"), cell("y").alias("cy"))
    around = own.withColumn("s", F.explode(F.sequence(F.lit(0), F.lit(8)))).select("id", "x", "y", (F.col("cx") + F.col("s") % 3 - 1).alias("cx"), (F.col("cy") + F.floor(F.col("s") / 3) - 1).alias("cy"))
    met = around.join(own.toDF("other", "ox", "oy", "cx", "cy"), ["cx", "cy"]).where("id <> other")
    distance = F.sqrt((F.col("x") - F.col("ox")) ** 2 + (F.col("y") - F.col("oy")) ** 2)
    return met.where(distance <= radius).select(F.col("id").alias("src"), F.col("other").alias("dst"), (1 / (distance + radius / 10)).alias("w"))


def statistics_step(stats: DataFrame, sums: DataFrame, n: int, dt: float) -> DataFrame:
    """S grows by the agents' sums less what the belief asks of n agents."""
    known = sums.select("k1", "k2", "total")
    return stats.join(F.broadcast(known), ["k1", "k2"]).select("k1", "k2", "norm", "lam", "mu", (F.col("s") + dt * (F.col("total") - n * F.col("mu"))).alias("s"))


def gradient(agents: DataFrame, stats: DataFrame) -> DataFrame:
    """(id, bx, by): weighted statistics along the gradient of the basis at each agent."""
    rows = agents.join(F.broadcast(stats), F.lit(True))
    w = F.col("lam") * F.col("s") / F.col("norm")
    bx = -F.col("k1") * PI * F.sin(F.col("k1") * PI * F.col("x")) * F.cos(F.col("k2") * PI * F.col("y"))
    by = -F.col("k2") * PI * F.cos(F.col("k1") * PI * F.col("x")) * F.sin(F.col("k2") * PI * F.col("y"))
    return rows.groupBy("id").agg(F.sum(w * bx).alias("bx"), F.sum(w * by).alias("by"))


def control(agents: DataFrame, slopes: DataFrame, dt: float, speed: float = 0.5) -> DataFrame:
    """Full speed against the slope, reflected at the walls; an agent without slope stays."""
    size = F.sqrt(F.col("bx") ** 2 + F.col("by") ** 2)
    fold = lambda c: F.when(c < 0, -c).when(c > 1, 2 - c).otherwise(c)
    move = lambda c, b: fold(F.col(c) - F.when(size > 1e-12, speed * dt * F.col(b) / size).otherwise(0.0))
    rest = [c for c in agents.columns if c not in ("id", "x", "y")]
    return agents.join(slopes, "id").select("id", move("x", "bx").alias("x"), move("y", "by").alias("y"), *rest)


def run(spark: SparkSession, agents: DataFrame, functions: DataFrame, steps: int, dt: float = 0.05, speed: float = 0.5, mode: str = "central", label=None, scratch: Scratch | None = None, method: str = "midpoint") -> tuple[DataFrame, DataFrame]:
    """(trajectories ``(t, id, x, y)``, statistics) of a search.

    ``mode='clustered'`` groups the agents anew at each step by ``label(agents)`` and adds cluster sums; the
    trajectories equal the central ones, as sums do. A step is one Runge-Kutta piece: ``midpoint`` of second order, or ``rk4``.
    """
    scratch = scratch or Scratch(spark, "search")
    n = agents.count()
    stats = scratch.save(functions.withColumn("s", F.lit(0.0)))
    if stats.count() > BROADCAST_ROWS:
        raise ValueError("a basis is a fixed small set")
    pieces = [agents.select(F.lit(0).alias("t"), "id", "x", "y")]

    def sums(now: DataFrame) -> DataFrame:
        if mode == "central":
            return central_sum(now, functions)
        return clustered_sum(now.join(label(now.select("id", "x", "y")), "id"), functions)

    for t in range(1, steps + 1):
        if method == "rk4":
            agents, stats = rk4_step(agents, stats, sums, n, dt, speed, scratch)
        else:
            half = scratch.save(statistics_step(stats, sums(agents), n, dt / 2))
            middle = scratch.save(control(agents, gradient(agents, half), dt / 2, speed))
            stats = scratch.save(statistics_step(stats, sums(middle), n, dt))
            agents = scratch.save(control(agents, gradient(middle, stats), dt, speed))
        pieces.append(agents.select(F.lit(t).alias("t"), "id", "x", "y"))
    out = pieces[0]
    for piece in pieces[1:]:
        out = out.unionByName(piece)
    return out, stats


def rk4_step(agents: DataFrame, stats: DataFrame, sums, n: int, dt: float, speed: float, scratch: Scratch) -> tuple[DataFrame, DataFrame]:
    """One classical fourth-order step of agents and statistics together; four passes of sums and slopes."""
    fold = lambda c: F.when(c < 0, -c).when(c > 1, 2 - c).otherwise(c)
    here = agents.select("id", "x", "y", F.col("x").alias("x0"), F.col("y").alias("y0"), F.lit(0.0).alias("ax"), F.lit(0.0).alias("ay"))
    there = stats.withColumns({"s0": F.col("s"), "ds": F.lit(0.0)})
    size = F.sqrt(F.col("bx") ** 2 + F.col("by") ** 2)
    way = lambda b: F.when(size > 1e-12, -speed * F.col(b) / size).otherwise(0.0)
    for share, weight in STAGES["rk4"]:
        grow = F.col("total") - n * F.col("mu")
        new = there.join(F.broadcast(sums(here).select("k1", "k2", "total")), ["k1", "k2"]).select("k1", "k2", "norm", "lam", "mu", (F.col("s0") + dt * share * grow).alias("s"), "s0", (F.col("ds") + weight * grow).alias("ds"))
        moved = here.join(gradient(here, there), "id").select(
            "id", fold(F.col("x0") + dt * share * way("bx")).alias("x"), fold(F.col("y0") + dt * share * way("by")).alias("y"), "x0", "y0",
            (F.col("ax") + weight * way("bx")).alias("ax"), (F.col("ay") + weight * way("by")).alias("ay"),
        )
        here, there = scratch.save(moved), scratch.save(new)
    done = here.select("id", fold(F.col("x0") + dt * F.col("ax")).alias("x"), fold(F.col("y0") + dt * F.col("ay")).alias("y"))
    return scratch.save(done), scratch.save(there.select("k1", "k2", "norm", "lam", "mu", (F.col("s0") + dt * F.col("ds")).alias("s")))


def coverage(stats: DataFrame) -> DataFrame:
    """(coverage): weighted squares of the statistics; 0 is perfect."""
    return stats.agg(F.sum(F.col("lam") * F.col("s") * F.col("s")).alias("coverage"))


def trajectory_gap(a: DataFrame, b: DataFrame) -> DataFrame:
    """(gap): the largest distance of an agent's two places at a step; infinite where one of them is missing."""
    both = a.join(b.toDF("t", "id", "x2", "y2"), ["t", "id"], "full")
    apart = F.sqrt((F.col("x") - F.col("x2")) ** 2 + (F.col("y") - F.col("y2")) ** 2)
    return both.agg(F.max(F.coalesce(apart, F.lit(float("inf")))).alias("gap"))
