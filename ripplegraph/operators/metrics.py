"""Accuracy and cost measures of partitions, modes and runs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _sides(edges: DataFrame, labels: DataFrame, column: str = "group_rep") -> DataFrame:
    own = labels.select(F.col("id"), F.col(column).alias("c"))
    return edges.join(own.toDF("src", "a"), "src").join(own.toDF("dst", "b"), "dst")


def cut_weight(edges: DataFrame, labels: DataFrame, column: str = "group_rep") -> DataFrame:
    """(cut): weight of links between clusters, each link once."""
    return _sides(edges, labels, column).agg((F.sum(F.when(F.col("a") != F.col("b"), F.col("w")).otherwise(0.0)) / 2).alias("cut"))


def cluster_cuts(edges: DataFrame, labels: DataFrame, column: str = "group_rep") -> DataFrame:
    """(cluster, size, cut, volume, ratio, ncut) of each cluster."""
    sized = labels.groupBy(F.col(column).alias("cluster")).agg(F.count("*").alias("size"))
    sums = _sides(edges, labels, column).groupBy(F.col("a").alias("cluster")).agg(F.sum(F.when(F.col("a") != F.col("b"), F.col("w")).otherwise(0.0)).alias("cut"), F.sum("w").alias("volume"))
    return sized.join(sums, "cluster").select("cluster", "size", "cut", "volume", (F.col("cut") / F.col("size")).alias("ratio"), (F.col("cut") / F.col("volume")).alias("ncut"))


def ratio_cut(edges: DataFrame, labels: DataFrame, column: str = "group_rep") -> DataFrame:
    return cluster_cuts(edges, labels, column).agg(F.sum("ratio").alias("ratio_cut"))


def normalised_cut(edges: DataFrame, labels: DataFrame, column: str = "group_rep") -> DataFrame:
    return cluster_cuts(edges, labels, column).agg(F.sum("ncut").alias("ncut"))


def agreement(a: DataFrame, b: DataFrame) -> DataFrame:
    """(agreement, equal): share of equal bits of two cuts in two, up to a flip; labels as ``bit`` 0 or 1."""
    both = a.select("id", F.col("bit").alias("x")).join(b.select("id", F.col("bit").alias("y")), "id")
    share = F.avg(F.when(F.col("x") == F.col("y"), 1.0).otherwise(0.0))
    return both.agg(F.greatest(share, 1 - share).alias("agreement")).withColumn("equal", F.col("agreement") == 1.0)


def contingency(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """(cluster, truth, n) with margins, null where summed over."""
    both = pred.select("id", "cluster").join(truth.select("id", "truth"), "id")
    return both.cube("cluster", "truth").agg(F.count("*").alias("n"))


def rand_index(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """(ari): adjusted Rand index."""
    both = pred.select("id", "cluster").join(truth.select("id", "truth"), "id")
    pairs = lambda c: F.col(c) * (F.col(c) - 1) / 2
    cells = both.groupBy("cluster", "truth").agg(F.count("*").alias("n"))
    x = cells.agg(F.sum(pairs("n")).alias("x"), F.sum("n").alias("all"))
    a = cells.groupBy("cluster").agg(F.sum("n").alias("n")).agg(F.sum(pairs("n")).alias("a"))
    b = cells.groupBy("truth").agg(F.sum("n").alias("n")).agg(F.sum(pairs("n")).alias("b"))
    joined = x.crossJoin(a).crossJoin(b).withColumn("expected", F.col("a") * F.col("b") / pairs("all"))
    top = (F.col("a") + F.col("b")) / 2 - F.col("expected")
    return joined.select(F.when(top == 0, 1.0).otherwise((F.col("x") - F.col("expected")) / top).alias("ari"))


def nmi(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """(nmi): mutual information over the mean entropy."""
    both = pred.select("id", "cluster").join(truth.select("id", "truth"), "id")
    cells = both.groupBy("cluster", "truth").agg(F.count("*").alias("n"))
    total = cells.agg(F.sum("n").alias("all"))
    rows, cols = cells.groupBy("cluster").agg(F.sum("n").alias("r")), cells.groupBy("truth").agg(F.sum("n").alias("c"))
    entropy = lambda frame, n, name: frame.crossJoin(total).agg((-F.sum(F.col(n) / F.col("all") * F.log(F.col(n) / F.col("all")))).alias(name))
    shared = cells.join(rows, "cluster").join(cols, "truth").crossJoin(total).agg(F.sum(F.col("n") / F.col("all") * F.log(F.col("n") * F.col("all") / (F.col("r") * F.col("c")))).alias("i"))
    joined = shared.crossJoin(entropy(rows, "r", "h")).crossJoin(entropy(cols, "c", "g"))
    mean = (F.col("h") + F.col("g")) / 2
    return joined.select(F.when(mean == 0, 1.0).otherwise(F.col("i") / mean).alias("nmi"))


def purity(pred: DataFrame, truth: DataFrame) -> DataFrame:
    cells = pred.select("id", "cluster").join(truth.select("id", "truth"), "id").groupBy("cluster", "truth").agg(F.count("*").alias("n"))
    return cells.groupBy("cluster").agg(F.max("n").alias("top"), F.sum("n").alias("n")).agg((F.sum("top") / F.sum("n")).alias("purity"))


def recovery(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """(errors, n): nodes outside the majority truth of their cluster."""
    cells = pred.select("id", "cluster").join(truth.select("id", "truth"), "id").groupBy("cluster", "truth").agg(F.count("*").alias("n"))
    return cells.groupBy("cluster").agg((F.sum("n") - F.max("n")).alias("lost"), F.sum("n").alias("n")).agg(F.sum("lost").alias("errors"), F.sum("n").alias("n"))


def messages(edges: DataFrame, steps: int, width: int = 1) -> DataFrame:
    """(messages): numbers sent in a run, one of ``width`` numbers over each direction of each link and step."""
    return edges.agg((F.count("*") * steps * width).alias("messages"))


def state_bytes(seeds: int, frequencies: int = 0, history: int = 0) -> int:
    """Bytes a node keeps: two values per start, two sums per start and frequency, and a history if kept."""
    return 8 * seeds * (2 + 2 * frequencies + history)


def gather_messages(n: int, k: int) -> int:
    """Numbers sent when each node learns k whole vectors."""
    return n * n * k


def max_amplitude(history: DataFrame) -> DataFrame:
    """(t, amplitude) over ``history(id, t, u)``."""
    return history.groupBy("t").agg(F.max(F.abs("u")).alias("amplitude"))


def frequency_error(found: DataFrame, exact: DataFrame) -> DataFrame:
    """(j, omega_error, lam_error) of ``found(j, omega, lam)`` against ``exact(j, omega, lam)``."""
    e = exact.select("j", F.col("omega").alias("o"), F.col("lam").alias("l"))
    return found.join(e, "j").select("j", F.abs(F.col("omega") - F.col("o")).alias("omega_error"), F.abs(F.col("lam") - F.col("l")).alias("lam_error"))


def vector_angle(a: DataFrame, b: DataFrame, nodes: DataFrame) -> DataFrame:
    """(j, angle) between degree-weighted vectors ``(id, j, component)``, in radians, without sign."""
    both = a.toDF("id", "j", "x").join(b.toDF("id", "j", "y"), ["id", "j"]).join(nodes.select("id", "deg"), "id")
    dot: Column = F.sum(F.col("deg") * F.col("x") * F.col("y"))
    size = F.sqrt(F.sum(F.col("deg") * F.col("x") ** 2) * F.sum(F.col("deg") * F.col("y") ** 2))
    return both.groupBy("j").agg(F.acos(F.least(F.abs(dot) / size, F.lit(1.0))).alias("angle"))


def steps_to_stable(by_step: DataFrame, tol: float = 0.02) -> DataFrame:
    """(steps): the first of ``(steps, omega)`` after which the frequency stays within ``tol`` of its last value."""
    last = by_step.agg(F.max_by("omega", "steps").alias("final"))
    off = by_step.crossJoin(F.broadcast(last)).withColumn("off", F.abs(F.col("omega") / F.col("final") - 1) > tol)
    worst = off.agg(F.coalesce(F.max(F.when(F.col("off"), F.col("steps"))), F.lit(-1)).alias("worst"))
    return off.crossJoin(F.broadcast(worst)).where(F.col("steps") > F.col("worst")).agg(F.min("steps").alias("steps"))
