"""Methods that waves are compared with: exact spectra, heat, random walks, power and orthogonal iteration, cuts."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ripplegraph.operators import wave
from ripplegraph.operators.cluster import LABELS, LocalGraph, codes
from ripplegraph.operators.graph import degrees, walk_weights
from ripplegraph.plans.ordered import ordered
from ripplegraph.plans.scratch import Scratch


def exact_pairs(g: LocalGraph) -> tuple[np.ndarray, np.ndarray]:
    """Eigenvalues and degree-unit eigenvectors of the walk Laplacian, in rising order."""
    values, vectors = np.linalg.eigh(g.dense())
    return values, vectors / np.sqrt(g.deg)[:, None]


def _guard(edges: DataFrame, max_nodes: int) -> None:
    n = edges.select("src").distinct().count()
    if n > max_nodes:
        raise ValueError(f"{n} nodes are more than the {max_nodes} that an exact decomposition may hold")


def spectral_exact(edges: DataFrame, k: int = 1, max_nodes: int = 5_000) -> DataFrame:
    """Labels by the signs of exact eigenvectors, of a connected graph of a checked size."""
    _guard(edges, max_nodes)

    def labels(part: pd.DataFrame) -> pd.DataFrame:
        g = LocalGraph.of(part["src"].to_numpy(), part["dst"].to_numpy(), part["w"].to_numpy())
        _, v = exact_pairs(g)
        coef = v[:, 1 : k + 1]
        bits, cluster = codes(coef)
        margin = (np.abs(coef) / np.sqrt((g.deg[:, None] * coef**2).sum(axis=0) / g.deg.sum())).min(axis=1)
        return pd.DataFrame({"id": g.ids, "bits": list(bits), "cluster": cluster, "group_rep": pd.Series(g.ids).groupby(cluster).transform("min"), "margin": margin})

    return edges.groupBy(F.lit(0).alias("all")).applyInPandas(labels, LABELS)


def eigenvalues_exact(edges: DataFrame, max_nodes: int = 5_000) -> DataFrame:
    """(j, lam) from j = 0, of a graph of a checked size."""
    _guard(edges, max_nodes)

    def values(part: pd.DataFrame) -> pd.DataFrame:
        g = LocalGraph.of(part["src"].to_numpy(), part["dst"].to_numpy(), part["w"].to_numpy())
        v, _ = exact_pairs(g)
        return pd.DataFrame({"j": np.arange(len(v)), "lam": v})

    return edges.groupBy(F.lit(0).alias("all")).applyInPandas(values, "j int, lam double")


def heat(spark: SparkSession, edges: DataFrame, state: DataFrame, steps: int, kappa: float = 1.0, scratch: Scratch | None = None, unroll: int = 8) -> DataFrame:
    """State after ``steps`` of u - kappa * (u - mean of the neighbours)."""
    scratch = scratch or Scratch(spark, "heat")
    rows, few = wave.laid_out(wave.with_own_rows(walk_weights(edges)), scratch)
    state = wave.one_task(state, few)
    for t in range(1, steps + 1):
        state = wave.step(rows, state, 1 - kappa, 0.0, kappa)
        if t % unroll == 0 and t < steps:
            state = wave.one_task(scratch.save(state), few)
    return scratch.save(state)


def random_walk(spark: SparkSession, edges: DataFrame, start: DataFrame, steps: int, lazy: bool = False, scratch: Scratch | None = None, unroll: int = 8, eps: float = 0.0) -> DataFrame:
    """(id, pi): the distribution after ``steps`` from ``start(id, pi)``; entries under ``eps`` are dropped each step."""
    scratch = scratch or Scratch(spark, "walk")
    rows, few = wave.laid_out(walk_weights(edges, "lazy" if lazy else "walk").select("src", "dst", "p"), scratch, "src")
    now = wave.one_task(start, few)
    for t in range(1, steps + 1):
        now = rows.join(now, rows["src"] == now["id"]).groupBy("dst").agg(F.sum(F.col("p") * F.col("pi")).alias("pi")).withColumnRenamed("dst", "id")
        if eps:
            now = now.where(F.col("pi") >= eps)
        if t % unroll == 0 and t < steps:
            now = wave.one_task(scratch.save(now), few)
    return scratch.save(now)


def sweep(edges: DataFrame, scores: DataFrame, scratch: Scratch | None = None) -> DataFrame:
    """(id, place, cut, volume, conductance) along falling ``score``, from place 1; nodes without a score are never in the set."""
    scratch = scratch or Scratch(edges.sparkSession, "sweep")
    deg = degrees(edges)
    total = deg.agg(F.sum("deg").alias("total"))
    falling = [F.desc("score"), F.asc("id")]
    placed = scratch.save(ordered(scores.join(deg, "id"), falling, scratch))
    at = placed.select("id", "place")
    known = edges.join(at.toDF("src", "a"), "src").join(at.toDF("dst", "b"), "dst", "left")
    inner = known.where("b < a").groupBy(F.col("src").alias("id")).agg(F.sum("w").alias("inner"))
    own = placed.drop("place").join(inner, "id", "left")
    sums = ordered(own, falling, scratch, {"volume": F.col("deg"), "cut": F.col("deg") - 2 * F.coalesce("inner", F.lit(0.0))})
    small = F.least("volume", F.col("total") - F.col("volume"))
    return sums.crossJoin(F.broadcast(total)).select("id", (F.col("place") + 1).alias("place"), "cut", "volume", F.when(small > 1e-9 * F.col("total"), F.col("cut") / small).alias("conductance"))


def truncated_walk(spark: SparkSession, edges: DataFrame, node: int, eps: float = 1e-4, steps: int = 20) -> DataFrame:
    """(id, place, ..., inside): the best sweep set of a truncated lazy walk from one node, by probability over degree."""
    start = spark.createDataFrame([(node, 1.0)], "id long, pi double")
    pi = random_walk(spark, edges, start, steps, lazy=True, eps=eps)
    scores = pi.join(degrees(edges), "id").select("id", (F.col("pi") / F.col("deg")).alias("score"))
    swept = sweep(edges, scores)
    best = swept.where("conductance is not null").agg(F.min_by("place", F.struct("conductance", "place")).alias("best"))
    return swept.crossJoin(F.broadcast(best)).withColumn("inside", F.col("place") <= F.col("best")).drop("best")


def power(spark: SparkSession, edges: DataFrame, state: DataFrame, steps: int, scratch: Scratch | None = None) -> DataFrame:
    """Lazy power iteration, degree-orthogonal to the constant vector: state with u0 near the second eigenvector."""
    n = sum(1 for c in state.columns if c[0] == "u" and c[1:].isdigit())
    mean = state.agg(*((F.sum(F.col("deg") * F.col(f"u{r}")) / F.sum("deg")).alias(f"m{r}") for r in range(n)))
    centred = state.crossJoin(F.broadcast(mean)).select("id", "deg", *((F.col(f"u{r}") - F.col(f"m{r}")).alias(f"u{r}") for r in range(n)), *(F.lit(0.0).alias(f"v{r}") for r in range(n)))
    return heat(spark, edges, centred, steps, 0.5, scratch)


def orthogonal(spark: SparkSession, edges: DataFrame, state: DataFrame, rounds: int, every: int = 4, scratch: Scratch | None = None) -> tuple[DataFrame, np.ndarray]:
    """Block iteration of the lazy walk with degree-orthonormal columns u0..: the state, and eigenvalue estimates.

    Every few rounds the driver gets one small Gram matrix and sends back its inverse root.
    """
    scratch = scratch or Scratch(spark, "orthogonal")
    n = sum(1 for c in state.columns if c[0] == "u" and c[1:].isdigit())
    values = np.zeros(n)
    done = 0
    while done < rounds:
        state = power(spark, edges, state, min(every, rounds - done), scratch)
        done += every
        pairs = [(a, b) for a in range(n) for b in range(a, n)]
        got = state.agg(*(F.sum(F.col("deg") * F.col(f"u{a}") * F.col(f"u{b}")).alias(f"g{a}_{b}") for a, b in pairs)).first()
        gram = np.zeros((n, n))
        for a, b in pairs:
            gram[a, b] = gram[b, a] = got[f"g{a}_{b}"]
        back = np.linalg.inv(np.linalg.cholesky(gram)).T
        mixed = [sum((F.col(f"u{a}") * float(back[a, b]) for a in range(n)), F.lit(0.0)).alias(f"u{b}") for b in range(n)]
        state = scratch.save(state.select("id", "deg", *mixed, *(F.lit(0.0).alias(f"v{r}") for r in range(n))))
    moved = heat(spark, edges, state, 1, 1.0, scratch)
    got = moved.agg(*(F.sum(F.col("deg") * F.col(f"v{a}") * F.col(f"u{b}")).alias(f"g{a}_{b}") for a in range(n) for b in range(n))).first()
    small = np.array([[got[f"g{a}_{b}"] for b in range(n)] for a in range(n)])
    values, turn = np.linalg.eigh((small + small.T) / 2)
    order = np.argsort(-values)
    turned = [sum((F.col(f"u{a}") * float(turn[a, b]) for a in range(n)), F.lit(0.0)).alias(f"u{i}") for i, b in enumerate(order)]
    return scratch.save(state.select("id", "deg", *turned)), 1 - values[order]


def _splits(spark: SparkSession, edges: DataFrame, max_nodes: int) -> DataFrame:
    """(mask, cut, size, n) of all splits of a tiny graph; the smallest id is always outside."""
    ids = edges.select("src").distinct().orderBy("src").limit(max_nodes + 1).toPandas()["src"].tolist()
    n = len(ids)
    if n > max_nodes:
        raise ValueError(f"more than {max_nodes} nodes")
    place = spark.createDataFrame([(i, k) for k, i in enumerate(ids)], "id long, k int")
    half = edges.where("src < dst").join(F.broadcast(place.toDF("src", "a")), "src").join(F.broadcast(place.toDF("dst", "b")), "dst").select("a", "b", "w")
    masks = spark.range(1, 1 << (n - 1)).select((F.col("id") * 2).alias("mask"))
    bit = lambda c: F.expr(f"shiftright(mask, {c}) & 1")
    return masks.crossJoin(F.broadcast(half)).groupBy("mask").agg(F.sum(F.when(bit("a") != bit("b"), F.col("w")).otherwise(0.0)).alias("cut")).select("mask", "cut", F.bit_count("mask").alias("size"), F.lit(n).alias("n"))


def minimum_cut(spark: SparkSession, edges: DataFrame, max_nodes: int = 16) -> DataFrame:
    """The split of least cut weight, balance or not, by trying all."""
    return _splits(spark, edges, max_nodes).orderBy("cut", "mask").limit(1)


def best_ratio_cut(spark: SparkSession, edges: DataFrame, max_nodes: int = 16) -> DataFrame:
    """The split of least cut over size, summed over both sides, by trying all."""
    ratio = F.col("cut") / F.col("size") + F.col("cut") / (F.col("n") - F.col("size"))
    return _splits(spark, edges, max_nodes).withColumn("ratio", ratio).orderBy("ratio", "mask").limit(1)


def pair_swap(edges: DataFrame, labels: DataFrame, passes: int = 10, max_nodes: int = 5_000) -> DataFrame:
    """(id, bit): the split ``labels(id, bit)`` of a graph of a checked size, improved by swaps of pairs; sizes stay."""
    _guard(edges, max_nodes)

    def swapped(part: pd.DataFrame) -> pd.DataFrame:
        known = part[part["dst"] >= 0]
        inside = swap_pairs(known, set(part[(part["dst"] < 0) & (part["w"] == 1.0)]["src"].tolist()), passes)
        ids = np.unique(known["src"])
        return pd.DataFrame({"id": ids, "bit": np.isin(ids, list(inside)).astype(int)})

    both = edges.select("src", "dst", "w").unionByName(labels.select(F.col("id").alias("src"), F.lit(-1).cast("long").alias("dst"), F.col("bit").cast("double").alias("w")))
    return both.groupBy(F.lit(0).alias("all")).applyInPandas(swapped, "id long, bit int")


def swap_pairs(edges: pd.DataFrame, inside: set[int], passes: int = 10) -> set[int]:
    """Swap the best pair of a split while that lowers the cut."""
    g = LocalGraph.of(edges["src"].to_numpy(), edges["dst"].to_numpy(), edges["w"].to_numpy())
    n = len(g.ids)
    w = np.zeros((n, n))
    w[g.src, g.dst] = g.p * g.deg[g.src]
    side = np.isin(g.ids, list(inside))
    for _ in range(passes * n):
        sign = np.where(side, 1.0, -1.0)
        gain = -(w @ sign) * sign  # cut weight minus inner weight of each node
        a, b = np.flatnonzero(side), np.flatnonzero(~side)
        both = gain[a][:, None] + gain[b][None, :] - 2 * w[np.ix_(a, b)]
        i, j = np.unravel_index(np.argmax(both), both.shape)
        if both[i, j] <= 1e-12:
            break
        side[a[i]], side[b[j]] = False, True
    return set(g.ids[side].tolist())
