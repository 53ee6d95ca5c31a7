"""Clusters from waves: signs of the lowest modes, as a local batch per component or as distributed steps.

Components of at most ``max_nodes`` nodes and ``max_edges`` rows are each handled whole in one Arrow batch: one
shuffle in all, whatever the number of steps. Larger ones run as distributed waves in two passes from one
reproducible start: the first reads probes only and finds the frequencies, the second keeps the matched
sums of those frequencies with each node.
"""

from __future__ import annotations

import math
import uuid
import warnings
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ripplegraph.functions.bounds import DEFAULT_C2, check_speed
from ripplegraph.operators import wave
from ripplegraph.operators.components import components
from ripplegraph.operators.graph import nodes_of
from ripplegraph.operators.spectrum import music
from ripplegraph.plans.ordered import ordered
from ripplegraph.plans.scratch import Scratch, bounded_broadcast

#: Steps whose probes are fetched at once.
SPAN = 256
#: A task of small components gets about so many nodes.
NODES_PER_TASK = 500
LABELS = "id long, bits array<int>, cluster long, group_rep long, margin double"


@dataclass(frozen=True)
class Preset:
    """Choices that decide how well signs are read."""

    seeds: int = 8
    center: bool = True
    window: str = "hann"
    align: bool = True
    prominence: float = 3.0
    eta: float = 10.0
    frequencies: str = "peaks"  # or "subspace", for frequencies that are too close for the bins of the run
    closed: bool = False  # small components in batches: Fourier sums from the ends of a run, without its steps
    parted: float = 0.0  # without given steps: doubled until no peak holds more than this share of a second mode; 0: only the lowest peak is looked at


ROBUST = Preset()
LITERAL = Preset(seeds=1, center=False, window="rect", align=False, prominence=1.0, eta=6.5)
_M = 2147483647


def start_values(ids: np.ndarray, seed: int) -> np.ndarray:
    """The same numbers as ``wave.start_value``."""
    own = np.mod(ids.astype(np.int64), _M)
    h = np.mod(own * 48271 + seed * 16807 + 12345, _M)
    return np.mod(np.mod(h * h, _M) + own * 7919, _M) / _M


def window_values(kind: str, steps: int) -> np.ndarray:
    return np.array([wave.window_value(kind, t, steps) for t in range(1, steps + 1)])


@dataclass
class LocalGraph:
    """One component in memory, nodes in id order."""

    ids: np.ndarray
    src: np.ndarray
    dst: np.ndarray
    p: np.ndarray
    deg: np.ndarray

    @classmethod
    def of(cls, src: np.ndarray, dst: np.ndarray, w: np.ndarray) -> LocalGraph:
        ids, flat = np.unique(np.concatenate((src, dst)), return_inverse=True)
        a, b = flat[: len(src)], flat[len(src) :]
        deg = np.bincount(a, w, len(ids))
        order = np.lexsort((b, a))
        a, b, w = a[order], b[order], w[order]
        return cls(ids, a, b, w / deg[a], deg)

    def mean_of_neighbours(self, u: np.ndarray) -> np.ndarray:
        out = np.empty_like(u)
        for r in range(u.shape[1]):
            out[:, r] = np.bincount(self.src, self.p * u[self.dst, r], len(self.ids))
        return out

    def evolve(self, u: np.ndarray, steps: int, c2: float) -> np.ndarray:
        """History (node, start, step) of ``steps`` updates."""
        out = np.empty((*u.shape, steps))
        before = u
        for t in range(steps):
            before, u = u, 2 * u - before - c2 * (u - self.mean_of_neighbours(u))
            out[:, :, t] = u
        return out

    def start(self, preset: Preset, seed: int = 0) -> np.ndarray:
        u = np.column_stack([start_values(self.ids, seed + r) for r in range(preset.seeds)])
        return u - (self.deg @ u) / self.deg.sum() if preset.center else u

    def dense(self) -> np.ndarray:
        """The symmetric form of the Laplacian."""
        n = len(self.ids)
        w = np.zeros((n, n))
        w[self.src, self.dst] = self.p * np.sqrt(self.deg[self.src] / self.deg[self.dst])
        return np.eye(n) - (w + w.T) / 2


def find_peaks(power: np.ndarray, k: int, prominence: float, reach: int = 4) -> np.ndarray:
    """Bins of the k lowest peaks; same rule as ``spectrum.peaks``."""
    n = len(power)
    out = []
    for b in range(1, n):
        left, right = power[b - 1], power[b + 1] if b + 1 < n else 0.0
        low = min(power[max(b - reach, 0) : b].min(initial=np.inf), power[b + 1 : b + 1 + reach].min(initial=np.inf) if b + 1 < n else 0.0)
        if power[b] > left and power[b] >= right and power[b] >= prominence * low:
            out.append(b)
            if len(out) == k:
                break
    return np.array(out, dtype=int)


def combine(y: np.ndarray, deg: np.ndarray, align: bool) -> np.ndarray:
    """One real coefficient per node from complex ones of several starts (node x start)."""
    if align:
        turn = 0.5 * np.angle((deg[:, None] * y * y).sum())
        y = y * np.exp(-1j * turn)
    real = y.real
    if real.shape[1] == 1:
        return real[:, 0]
    values, vectors = np.linalg.eigh((real * deg[:, None]).T @ real)
    return real @ vectors[:, -1]


def codes(coef: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bits (node x mode), flipped so that the first node has 1, and their number."""
    bits = (coef > 0).astype(np.int32)
    if len(bits):
        bits = np.where(bits[0] == 1, bits, 1 - bits)
    return bits, bits @ (1 << np.arange(bits.shape[1])) if bits.shape[1] else np.zeros(len(bits), dtype=np.int64)


#: Components up to so many nodes are read from closed sums of a run, from so many steps on.
CLOSED_NODES, CLOSED_STEPS = 256, 512


def ends_of(g: LocalGraph, u: np.ndarray, steps: int, c2: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(update matrix, state after ``steps``, a power of two, and after one more): u(t + s) = C(s) u(t) - u(t - s), and C(2s) = C(s)**2 - 2."""
    n = len(g.ids)
    m = np.zeros((n, n))
    m[g.src, g.dst] = c2 * g.p
    m[np.arange(n), np.arange(n)] += 2 - c2
    c, now, s = m, m @ u - u, 1  # the state after s steps; the one before the start equals the start
    after = m @ now - u
    while s < steps:
        c_now, c_after = c @ now - u, c @ after - (m @ u - u)
        c, now, after, s = c @ c - 2 * np.eye(n), c_now, c_after, 2 * s
    return m, now, after


def closed_sums(g: LocalGraph, u: np.ndarray, steps: int, c2: float, chunk: int = 32) -> Iterator[np.ndarray]:
    """Hann-windowed Fourier sums (node x start x bin) of a centred run of ``steps``, some bins at a time from 0.

    Summed over a run, u(t + 1) + u(t - 1) = M u(t) gives (2 cos w - M) S(w) from the two ends of the run, so no step in
    between is needed; the window joins three neighbouring bins. The constant mode, which is not in the run, is moved away.
    """
    m, last, beyond = ends_of(g, u, steps, c2)
    first, n, turn = m @ u - u, len(g.ids), 2 * np.pi / steps
    base = np.outer(np.ones(n), g.deg / g.deg.sum()) - m
    for low in range(0, steps // 2, chunk):
        w = turn * np.arange(low - 1, low + chunk + 1)
        a = base[None] + 2 * np.cos(w)[:, None, None] * np.eye(n)[None]
        right = (first - beyond)[None] - np.exp(-1j * w)[:, None, None] * (u - last)[None]
        both = np.linalg.solve(a, np.concatenate((right.real, right.imag), axis=2))
        sums = (both[:, :, : u.shape[1]] + 1j * both[:, :, u.shape[1] :]).transpose(1, 2, 0)
        yield 0.5 * sums[:, :, 1:-1] - 0.25 * (np.exp(-0.5j * turn) * sums[:, :, :-2] + np.exp(0.5j * turn) * sums[:, :, 2:])


def closed_modes(g: LocalGraph, k: int, c2: float, steps: int, preset: Preset, seed: int = 0, reach: int = 4) -> tuple[np.ndarray, np.ndarray]:
    """As ``local_modes`` reads peaks, from as many bins as the k lowest peaks take."""
    z = power = None
    found = np.zeros(0, dtype=int)
    for part in closed_sums(g, g.start(preset, seed), steps, c2):
        own = (g.deg[:, None, None] * np.abs(part) ** 2).sum(axis=(0, 1))
        z, power = (part, own) if z is None else (np.concatenate((z, part), axis=2), np.concatenate((power, own)))
        found = find_peaks(power, k + 1, preset.prominence)
        found = found[found < len(power) - reach - 1][:k]  # the bins after a peak are known
        if len(found) == k:
            break
    else:
        found = find_peaks(power, k, preset.prominence)
    return 2 * np.pi * found / steps, np.column_stack([combine(z[:, :, b], g.deg, preset.align) for b in found]) if len(found) else np.zeros((len(g.ids), 0))


def local_modes(g: LocalGraph, k: int, c2: float, steps: int, preset: Preset, seed: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """(frequencies, coefficients node x mode) of the lowest peaks of one component."""
    if preset.closed and preset.center and preset.window == "hann" and preset.frequencies == "peaks" and steps >= CLOSED_STEPS and steps & (steps - 1) == 0 and 1 < len(g.ids) <= CLOSED_NODES:
        return closed_modes(g, k, c2, steps, preset, seed)
    history = g.evolve(g.start(preset, seed), steps, c2)
    if not preset.center:
        history = history - history.mean(axis=2, keepdims=True)
    if preset.parted:
        history = without_mean(g, history)
    if preset.frequencies == "subspace":
        return subspace_modes(g, history, k, preset)
    z = np.fft.rfft(history * window_values(preset.window, steps), axis=2)
    power = (g.deg[:, None, None] * np.abs(z) ** 2).sum(axis=(0, 1))
    found = find_peaks(power, k, preset.prominence)
    return 2 * np.pi * found / steps, np.column_stack([combine(z[:, :, b], g.deg, preset.align) for b in found]) if len(found) else np.zeros((len(g.ids), 0))


def subspace_modes(g: LocalGraph, history: np.ndarray, k: int, preset: Preset, probes: int = 64, signals: int = 32) -> tuple[np.ndarray, np.ndarray]:
    """The same from a subspace estimate of the frequencies, which needs fewer steps to part two of them, and matched sums."""
    steps = history.shape[2]
    series = history.reshape(-1, steps)[:probes]
    found = music(series, min(256, steps // 2), min(signals, len(g.ids) - 1))[:k]
    t = np.arange(1, steps + 1)
    waves = np.exp(-1j * np.outer(found, t)) * window_values(preset.window, steps)
    z = np.einsum("nrt,jt->nrj", history, waves)
    return found, np.column_stack([combine(z[:, :, j], g.deg, preset.align) for j in range(len(found))]) if len(found) else np.zeros((len(g.ids), 0))


def settled(now: float | None, last: float | None, steps: int, preset: Preset, tol: float = 0.02) -> bool:
    """Whether the lowest peak has not moved against half of the steps, and they hold cycles enough of it."""
    return now is not None and last is not None and abs(now - last) <= max(tol * now, 2 * math.pi / steps) and now * steps >= 2 * math.pi * preset.eta


def without_mean(g: LocalGraph, history: np.ndarray) -> np.ndarray:
    """A centred history stays centred; what rounding adds to the constant mode grows with the steps and is taken off."""
    return history - np.tensordot(g.deg, history, (0, 0))[None] / g.deg.sum()


def shared(z: np.ndarray, deg: np.ndarray, b: int, reach: int = 2) -> float:
    """Power of a second mode around a bin of z (node x start x bin) against the first: 0 for one mode alone, as all starts then hear the same vector."""
    y = z[:, :, max(b - reach, 0) : b + reach + 1].reshape(len(z), -1)
    values = np.linalg.eigvalsh((y.conj() * deg[:, None]).T @ y)
    return float(values[-2] / values[-1]) if len(values) > 1 and values[-1] > 0 else 0.0


def parting_steps(g: LocalGraph, k: int, c2: float, preset: Preset, seed: int = 0, t_max: int = 1 << 16) -> int:
    """Smallest power of two of steps, not below ``stable_steps``, for which each of the k lowest peaks holds one mode; a warning if ``t_max`` does not do."""
    steps = stable_steps(g, c2, preset)
    while True:
        z = np.fft.rfft(without_mean(g, g.evolve(g.start(preset, seed), steps, c2)) * window_values(preset.window, steps), axis=2)
        found = find_peaks((g.deg[:, None, None] * np.abs(z) ** 2).sum(axis=(0, 1)), k, preset.prominence)
        if all(shared(z, g.deg, b) <= preset.parted for b in found):
            return steps
        if steps >= t_max:
            warnings.warn(f"peaks of the component of node {g.ids[0]} ({len(g.ids)} nodes) hold several modes after {steps} steps", stacklevel=2)
            return steps
        steps *= 2


def stable_steps(g: LocalGraph, c2: float, preset: Preset, t_max: int = 1 << 15, tol: float = 0.02) -> int:
    """Smallest power of two of steps for which the lowest peak is settled; a warning if none below ``t_max`` is."""
    steps, last = 64, None
    while steps < t_max:
        omega, _ = local_modes(g, 1, c2, steps, preset)
        now = omega[0] if len(omega) else None
        if settled(now, last, steps, preset, tol):
            return steps
        steps, last = steps * 2, now
    if len(g.ids) > 1:
        warnings.warn(f"the lowest peak of the component of node {g.ids[0]} ({len(g.ids)} nodes) is not settled before {t_max} steps", stacklevel=2)
    return steps


def probe_power(series: np.ndarray, preset: Preset, deg: np.ndarray | None = None) -> np.ndarray:
    """Power by bin of a history (probe, start, step), weighted by degree as in a batch; the mean is taken off only where the start was not centred."""
    h = window_values(preset.window, series.shape[2])
    weight = np.ones(len(series)) if deg is None else deg
    flat = (lambda x: x) if preset.center else (lambda x: x - x.mean(axis=1, keepdims=True))
    return sum((weight[:, None] * np.abs(np.fft.rfft(flat(x) * h, axis=1)) ** 2).sum(axis=0) for x in series.transpose(1, 0, 2))


def stable_series(go: Callable[[int], np.ndarray], preset: Preset, t_max: int = 1 << 17, deg: np.ndarray | None = None) -> np.ndarray:
    """The history of the probes, doubled until their lowest peak is settled; ``go`` gives so many steps more."""
    series, last = go(64), None
    while True:
        steps = series.shape[2]
        power = probe_power(series, preset, deg)
        found = find_peaks(power, 1, preset.prominence)
        now = 2 * math.pi * int(found[0]) / steps if len(found) else None
        if settled(now, last, steps, preset) or not power.any():  # no power: a node of its own
            return series
        if steps >= t_max:
            raise RuntimeError(f"the lowest peak is not settled after {steps} steps; give the steps")
        series, last = np.concatenate((series, go(steps)), axis=2), now


def local_labels(edges: pd.DataFrame, k: int, c2: float, steps: int | None, preset: Preset, seed: int = 0) -> pd.DataFrame:
    return labels_of(LocalGraph.of(edges["src"].to_numpy(), edges["dst"].to_numpy(), edges["w"].to_numpy()), k, c2, steps, preset, seed)


def labels_of(g: LocalGraph, k: int, c2: float, steps: int | None, preset: Preset, seed: int = 0) -> pd.DataFrame:
    steps = steps or (parting_steps(g, k, c2, preset, seed) if preset.parted else stable_steps(g, c2, preset))
    _, coef = local_modes(g, k, c2, steps, preset, seed)
    bits, cluster = codes(coef)
    rms = np.sqrt((g.deg[:, None] * coef**2).sum(axis=0) / g.deg.sum()) if coef.shape[1] else np.ones(0)
    margin = (np.abs(coef) / np.maximum(rms, 1e-300)).min(axis=1) if coef.shape[1] else np.zeros(len(g.ids))
    rep = pd.Series(g.ids).groupby(cluster).transform("min").to_numpy()
    return pd.DataFrame({"id": g.ids, "bits": list(bits), "cluster": cluster, "group_rep": rep, "margin": margin})


def wave_cluster(spark: SparkSession, edges: DataFrame, k: int = 1, c2: float = DEFAULT_C2, steps: int | None = None, preset: Preset = ROBUST, seed: int = 0, max_nodes: int = 5_000, max_edges: int = 2_000_000, connected: bool = False, scratch: Scratch | None = None) -> DataFrame:
    """(id, bits, cluster, group_rep, margin): clusters of each component by the signs of its k lowest modes.

    ``cluster`` counts within a component; ``group_rep``, the smallest id of the cluster, is comparable
    everywhere. ``steps`` None: each component runs until its lowest peak is stable, by all nodes in a batch and by
    probes in distributed steps.
    """
    check_speed(c2)
    if preset.parted and (preset.seeds < 2 or not preset.center):
        raise ValueError("modes are told apart by several centred starts")
    scratch = scratch or Scratch(spark, "cluster")
    edges = scratch.save(edges)
    if connected:
        labelled = edges.withColumn("component", F.lit(0).cast("long"))
        few = edges.count() <= max_edges and edges.select("src").distinct().count() <= max_nodes
        sizes = {0: few}
        local, large = (labelled, None) if few else (None, [0])
    else:
        labels = components(spark, edges, scratch)
        n_nodes = labels.count()
        labelled = scratch.save(edges.join(bounded_broadcast(labels.withColumnRenamed("id", "src"), n_nodes), "src").select("src", "dst", "w", "component"))
        sizes = labelled.groupBy("component").agg(F.count("*").alias("rows"), F.count_distinct("src").alias("nodes"))
        big = scratch.save(sizes.where((F.col("rows") > max_edges) | (F.col("nodes") > max_nodes)).select("component"))
        n_large = big.count()
        large = (r[0] for r in big.toLocalIterator())
        local = labelled.join(bounded_broadcast(big, n_large), "component", "left_anti") if n_large else labelled
        tasks = min(int(spark.conf.get("spark.sql.shuffle.partitions")), n_nodes // NODES_PER_TASK)
        if tasks > 1:  # rows are few for their work, so their bytes must not decide how many share a task
            local = local.repartition(tasks, "component")
    out = None
    if local is not None:
        out = local.groupBy("component").applyInPandas(lambda part: local_labels(part, k, c2, steps, preset, seed), LABELS)
    kept, found = f"large-{uuid.uuid4().hex}", False
    for name in large or []:
        own = labelled.where(F.col("component") == name).select("src", "dst", "w")
        one = distributed_labels(spark, scratch.save(own), k, c2, steps, preset, seed, scratch)
        one.write.mode("append").parquet(scratch.path(kept))  # one table for all, so that the plan does not grow with them
        found = True
    if found:
        done = spark.read.schema(LABELS).parquet(scratch.path(kept))
        out = done if out is None else out.unionByName(done)
    return out


def distributed_labels(spark: SparkSession, edges: DataFrame, k: int, c2: float, steps: int | None, preset: Preset, seed: int, scratch: Scratch, n_probes: int = 64) -> DataFrame:
    """Labels of one component by distributed steps; the driver sees probe series and k small matrices."""
    nodes = scratch.save(nodes_of(edges))
    state = scratch.save(wave.initial_state(nodes, preset.seeds, "degree" if preset.center else "none", seed=seed))
    run = wave.Probes(spark, edges, state, n_probes, c2, scratch)

    def go(more: int) -> np.ndarray:
        """History (probe, start, step) of so many steps more: n_probes * more rows, fetched in spans."""
        parts = []
        while more:
            span = min(more, SPAN)
            seen = run.go(span).orderBy("id", "t").toPandas()
            parts.append(np.stack([seen[f"u{r}"].to_numpy().reshape(-1, span) for r in range(preset.seeds)], axis=1))
            more -= span
        return np.concatenate(parts, axis=2)

    if preset.parted and steps is None:
        raise ValueError("modes are told apart in batches only; give the steps of a distributed run")
    weights = np.array([r["deg"] for r in run.chosen.orderBy("id").collect()])  # n_probes at most
    series = stable_series(go, preset, deg=weights) if steps is None else go(steps)
    steps = series.shape[2]
    found = find_peaks(probe_power(series, preset, weights), k, preset.prominence)
    omegas = [2 * math.pi * int(b) / steps for b in found]
    done = wave.run(spark, edges, state, steps, c2, scratch, filters=omegas, window=preset.window)
    if not preset.center:
        done = wave.detrended_sums(done, omegas, steps, preset.window, preset.seeds)
    columns, first = [], None
    for j in range(len(omegas)):
        re, im = ([F.col(f"{part}{j}_{r}") for r in range(preset.seeds)] for part in ("re", "im"))
        d = F.col("deg")
        turn = done.agg(F.sum(d * sum((a * a - b * b for a, b in zip(re, im, strict=True)), F.lit(0.0))).alias("x"), F.sum(d * sum((2 * a * b for a, b in zip(re, im, strict=True)), F.lit(0.0))).alias("y")).first()
        theta = 0.5 * math.atan2(turn["y"], turn["x"]) if preset.align else 0.0
        real = [a * math.cos(theta) + b * math.sin(theta) for a, b in zip(re, im, strict=True)]
        pairs = [(a, b) for a in range(preset.seeds) for b in range(a, preset.seeds)]
        gram = done.agg(*(F.sum(d * real[a] * real[b]).alias(f"g{a}_{b}") for a, b in pairs)).first()
        matrix = np.zeros((preset.seeds, preset.seeds))
        for a, b in pairs:
            matrix[a, b] = matrix[b, a] = gram[f"g{a}_{b}"]
        best = np.linalg.eigh(matrix)[1][:, -1]
        columns.append(sum((x * float(c) for x, c in zip(real, best, strict=True)), F.lit(0.0)).alias(f"coef{j}"))
    coef = scratch.save(done.select("id", "deg", *columns))
    first = coef.orderBy("id").first()
    signs = [1.0 if first[f"coef{j}"] > 0 else -1.0 for j in range(len(omegas))]
    rms = coef.agg(*(F.sqrt(F.sum(F.col("deg") * F.col(f"coef{j}") ** 2) / F.sum("deg")).alias(f"s{j}") for j in range(len(omegas)))).first()
    bit = lambda j: F.when(F.col(f"coef{j}") * signs[j] > 0, 1).otherwise(0)
    bits = F.array(*(bit(j) for j in range(len(omegas)))).cast("array<int>")
    cluster = sum((F.shiftleft(bit(j), j) for j in range(len(omegas))), F.lit(0)).cast("long")
    margin = F.least(*(F.abs(F.col(f"coef{j}")) / float(rms[f"s{j}"]) for j in range(len(omegas))), F.lit(float("inf")), F.lit(float("inf")))
    coded = scratch.save(coef.select("id", bits.alias("bits"), cluster.alias("cluster"), margin.alias("margin")))
    reps = coded.groupBy("cluster").agg(F.min("id").alias("group_rep"))
    return coded.join(F.broadcast(reps), "cluster").select("id", "bits", "cluster", "group_rep", "margin")  # 2**k groups at most


def wave_bisect(spark: SparkSession, edges: DataFrame, **options) -> DataFrame:
    return wave_cluster(spark, edges, k=1, **options)


def recursive_bisect(spark: SparkSession, edges: DataFrame, depth: int, scratch: Scratch | None = None, **options) -> DataFrame:
    """(id, group_rep): each side is cut again, ``depth`` times; an answer for close frequencies."""
    scratch = scratch or Scratch(spark, "bisect")
    current = scratch.save(edges)
    labels = None
    for _ in range(depth):
        labels = scratch.save(wave_cluster(spark, current, k=1, scratch=scratch, **options).select("id", "group_rep"))
        side = lambda c, name: labels.toDF(c, name)  # noqa: B023, E731
        current = scratch.save(current.join(side("src", "a"), "src").join(side("dst", "b"), "dst").where("a = b").select("src", "dst", "w"))
    lost = edges.select(F.col("src").alias("id")).distinct().join(labels, "id", "left_anti")
    return labels.unionByName(lost.select("id", F.col("id").alias("group_rep")))


def relabel(labels: DataFrame, scratch: Scratch | None = None) -> DataFrame:
    """Adds ``label``, the clusters counted from 0 in the order of their representatives."""
    scratch = scratch or Scratch(labels.sparkSession, "relabel")
    reps = ordered(labels.select("group_rep").distinct(), ["group_rep"], scratch).withColumnRenamed("place", "label")
    return labels.join(reps, "group_rep")
