"""Spectra of node histories: discrete Fourier sums in SQL, whole transforms in Arrow, peaks, eigenpairs."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ripplegraph.functions.bounds import DEFAULT_C2, lambda_of
from ripplegraph.operators.wave import window_column


def detrended(history: DataFrame, how: str = "none") -> DataFrame:
    """``history(id, t, u)`` without its mean over time, without the degree-weighted mean of each step (needs deg), or as first differences."""
    if how == "mean":
        return history.withColumn("u", F.col("u") - F.avg("u").over(Window.partitionBy("id")))
    if how == "degree":
        mean = history.groupBy("t").agg((F.sum(F.col("deg") * F.col("u")) / F.sum("deg")).alias("mean"))
        return history.join(mean, "t").withColumn("u", F.col("u") - F.col("mean")).drop("mean")
    if how == "difference":
        return history.withColumn("u", F.col("u") - F.lag("u").over(Window.partitionBy("id").orderBy("t"))).where("u is not null")
    return history


def dft(history: DataFrame, bins: list[int], steps: int, window: str = "rect") -> DataFrame:
    """(id, bin, re, im) of ``history(id, t, u)`` at some bins: a sum that combines before its shuffle."""
    spread = history.withColumn("bin", F.explode(F.array(*(F.lit(b) for b in bins))))
    angle = F.col("bin") * F.col("t") * (2 * math.pi / steps)
    h = window_column(window, F.col("t"), steps)
    return spread.groupBy("id", "bin").agg(F.sum(h * F.col("u") * F.cos(angle)).alias("re"), F.sum(-h * F.col("u") * F.sin(angle)).alias("im"))


def dft_arrays(state: DataFrame, bins: list[int], steps: int, window: str = "rect") -> DataFrame:
    """The same from arrays of values: no explosion of the history, one row per node and bin."""
    spread = state.select("id", "series0", F.explode(F.array(*(F.lit(b) for b in bins))).alias("bin"))

    def part(wave) -> Column:
        terms = F.transform("series0", lambda u, i: u * window_column(window, i + 1, steps) * wave(F.col("bin") * (i + 1) * (2 * math.pi / steps)))
        return F.aggregate(terms, F.lit(0.0), lambda a, x: a + x)

    return spread.select("id", "bin", part(F.cos).alias("re"), (-part(F.sin)).alias("im"))


def fft(state: DataFrame, window: str = "hann", detrend: bool = True) -> DataFrame:
    """(id, bin, omega, re, im, power) of whole histories, by Arrow batches of ``series0``."""

    def rows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for node, series in zip(batch["id"], batch["series0"], strict=True):
                x = np.asarray(series, dtype=float)
                n = len(x)
                if n == 0:
                    continue
                t = np.arange(1, n + 1)
                h = {"rect": np.ones(n), "hann": 0.5 - 0.5 * np.cos(2 * np.pi * (t - 0.5) / n), "hamming": 0.54 - 0.46 * np.cos(2 * np.pi * (t - 0.5) / n), "blackman": 0.42 - 0.5 * np.cos(2 * np.pi * (t - 0.5) / n) + 0.08 * np.cos(4 * np.pi * (t - 0.5) / n)}[window]
                z = np.fft.rfft((x - x.mean() if detrend else x) * h) * np.exp(-2j * np.pi * np.arange(n // 2 + 1) / n)
                yield pd.DataFrame({"id": node, "bin": np.arange(len(z)), "omega": 2 * np.pi * np.arange(len(z)) / n, "re": z.real, "im": z.imag, "power": np.abs(z) ** 2})

    return state.select("id", "series0").mapInPandas(rows, "id long, bin int, omega double, re double, im double, power double")


def matched(history: DataFrame, omegas: list[float], steps: int, window: str = "hann", part: str = "cos") -> DataFrame:
    """(id, j, coef): windowed sums against cos(omega (t + 1/2)), the exact shape of a mode; or against sin for the other part."""
    spread = history.withColumn("o", F.explode(F.array(*(F.struct(F.lit(j + 1).alias("j"), F.lit(float(w)).alias("w")) for j, w in enumerate(omegas)))))
    angle = F.col("o.w") * (F.col("t") + 0.5) if part == "cos" else F.col("o.w") * F.col("t")
    wave = F.cos(angle) if part == "cos" else F.sin(angle)
    return spread.groupBy("id", F.col("o.j").alias("j")).agg(F.sum(window_column(window, F.col("t"), steps) * F.col("u") * wave).alias("coef"))


def pool(coefficients: DataFrame, nodes: DataFrame | None = None) -> DataFrame:
    """(bin, power) over all nodes, weighted by degree if ``nodes(id, deg)`` are given."""
    power = F.col("re") * F.col("re") + F.col("im") * F.col("im")
    if nodes is None:
        return coefficients.groupBy("bin").agg(F.sum(power).alias("power"))
    return coefficients.join(nodes.select("id", "deg"), "id").groupBy("bin").agg(F.sum(F.col("deg") * power).alias("power"))


def peaks(spectrum: DataFrame, k: int, steps: int, c2: float = DEFAULT_C2, prominence: float = 3.0, reach: int = 4, refine: bool = False, by: str | None = None) -> DataFrame:
    """(j, bin, omega, lam, power) of the k lowest peaks of ``spectrum(bin, power)``; per ``by`` if given.

    A peak is a bin above both neighbours and ``prominence`` times above the lowest of ``reach`` bins on either
    side: the hump of the bulk of eigenvalues cannot hide it. The constant mode at bin 0 is none.
    """
    keys = [by] if by else []
    order = Window.partitionBy(*keys).orderBy("bin")
    below = F.min("power").over(order.rowsBetween(-reach, -1))
    above = F.min("power").over(order.rowsBetween(1, reach))
    last, following = F.lag("power").over(order), F.lead("power").over(order)
    tops = spectrum.withColumns({"last": last, "following": following, "below": below, "above": above})
    is_top = (F.col("power") > F.coalesce("last", F.lit(0.0))) & (F.col("power") >= F.coalesce("following", F.lit(0.0))) & (F.col("power") >= prominence * F.least(F.coalesce("below", F.lit(0.0)), F.coalesce("above", F.lit(0.0))))
    shift = F.when(F.lit(refine), 0.5 * (F.log("last") - F.log("following")) / (F.log("last") - 2 * F.log("power") + F.log("following"))).otherwise(F.lit(0.0))
    found = tops.where((F.col("bin") > 0) & is_top).withColumn("omega", (F.col("bin") + F.coalesce(shift, F.lit(0.0))) * (2 * math.pi / steps))
    ranked = found.withColumn("j", F.row_number().over(Window.partitionBy(*keys).orderBy("bin"))).where(F.col("j") <= k)
    return ranked.select(*keys, "j", "bin", "omega", lambda_of("omega", c2).alias("lam"), "power")


def choose_k(found: DataFrame) -> DataFrame:
    """(k): number of peaks below the widest gap of their frequencies."""
    order = Window.orderBy("omega")
    gaps = found.withColumn("gap", F.lead("omega").over(order) - F.col("omega")).where("gap is not null")
    return gaps.agg(F.max_by("j", "gap").alias("k"))


def music(series: np.ndarray, order: int, k: int, grid: int = 4096) -> np.ndarray:
    """The k lowest frequencies of the subspace pseudo-spectrum of probe series (probes x steps)."""
    length = series.shape[1] - order + 1
    cov = np.zeros((order, order))
    for row in series - series.mean(axis=1, keepdims=True):
        blocks = np.lib.stride_tricks.sliding_window_view(row, order)
        cov += blocks.T @ blocks / length
    values, vectors = np.linalg.eigh(cov)
    noise = vectors[:, : max(order - 2 * k, 1)]
    omega = np.linspace(1e-3, np.pi, grid)
    steer = np.exp(-1j * np.outer(omega, np.arange(order)))
    pseudo = 1 / (np.abs(steer @ noise) ** 2).sum(axis=1)
    top = np.flatnonzero((pseudo[1:-1] > pseudo[:-2]) & (pseudo[1:-1] >= pseudo[2:])) + 1
    best = top[np.argsort(-pseudo[top])[:k]]
    return np.sort(omega[best])


def eigenvectors(modes: DataFrame, nodes: DataFrame) -> DataFrame:
    """(id, j, component): coefficients scaled to unit degree norm, positive at the smallest id."""
    known = modes.join(nodes.select("id", "deg"), "id")
    norm = known.groupBy("j").agg(F.sqrt(F.sum(F.col("deg") * F.col("coef") * F.col("coef"))).alias("norm"), F.signum(F.min_by("coef", "id")).alias("sign"))
    return known.join(F.broadcast(norm), "j").select("id", "j", (F.col("coef") / F.col("norm") * F.when(F.col("sign") == 0, 1).otherwise(F.col("sign"))).alias("component"))


def gather_vectors(vectors: DataFrame, limit: int = 100_000) -> DataFrame:
    """(j, vector): whole vectors in id order, as every node would hold them after a gather; refused above ``limit`` nodes."""
    n = vectors.select("id").distinct().count()
    if n > limit:
        raise ValueError(f"{n} nodes are more than the {limit} that a vector may hold")
    return vectors.groupBy("j").agg(F.transform(F.array_sort(F.collect_list(F.struct("id", "component"))), lambda x: x["component"]).alias("vector"))
