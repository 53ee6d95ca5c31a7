"""Clusters of points by waves over the links between near ones, whose links are never written out.

Points are dealt into square cells of half the radius, so that all points of a cell are near each other and a point's
neighbours lie at most two cells away. The weights between two cells are one block of a matrix: links grow with the
square of the points of a cell, and rows of an edge table would too. Where blocks fit in memory a batch holds
them for all its steps; else every step makes them anew from places, in tasks of some cells.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ripplegraph.functions.bounds import DEFAULT_C2, check_speed
from ripplegraph.operators.cluster import LABELS, ROBUST, LocalGraph, Preset, find_peaks, labels_of, start_values, wave_cluster, window_values
from ripplegraph.operators.components import components
from ripplegraph.operators.search import proximity
from ripplegraph.plans.ordered import ordered
from ripplegraph.plans.scratch import BROADCAST_BYTES, BROADCAST_ROWS, Scratch, bounded_broadcast

#: Blocks of at most so many bytes are held by one batch.
HELD_BYTES = 256 << 20
#: Below so many pairs of points to a pair of cells their links are rows of an edge table, which grows in proportion to the points.
PAIRS_OF_POINTS = 64
#: Rows of a block that are made at a time.
ROWS = 256


def weights(ax: np.ndarray, ay: np.ndarray, bx: np.ndarray, by: np.ndarray, radius: float, same: int | None) -> np.ndarray:
    """Weights as in ``proximity`` between points, 0 beyond the radius; a point ``same`` places on is the point itself, without a link."""
    out = ax[:, None] - bx
    out *= out
    up = ay[:, None] - by
    up *= up
    out += up
    np.sqrt(out, out=out)
    near = out <= radius
    out += radius / 10
    np.divide(near, out, out=out)
    if same is not None:
        out[np.arange(len(out)), same + np.arange(len(out))] = 0.0
    return out


@dataclass
class NearGraph(LocalGraph):
    """One component in memory: nodes in id order, weights as blocks between slices of ``order``, each pair of cells once."""

    order: np.ndarray = field(default_factory=lambda: np.zeros(0, dtype=int))
    blocks: list[tuple[slice, slice, np.ndarray]] = field(default_factory=list)

    def sums(self, u: np.ndarray) -> np.ndarray:
        v = u[self.order]
        total = np.zeros_like(v)
        for a, b, w in self.blocks:
            total[a] += w @ v[b]
            if a != b:
                total[b] += w.T @ v[a]
        out = np.empty_like(total)
        out[self.order] = total
        return out

    def mean_of_neighbours(self, u: np.ndarray) -> np.ndarray:
        return self.sums(u) / self.deg[:, None]


def near_graphs(points: pd.DataFrame, radius: float) -> list[NearGraph]:
    """The components of points with distinct ids that have a link, by their smallest id."""
    points = points.sort_values(["cx", "cy", "id"])
    ids, x, y = (points[c].to_numpy() for c in ("id", "x", "y"))
    cell = list(zip(points["cx"].tolist(), points["cy"].tolist(), strict=True))
    starts = [i for i in range(len(cell)) if i == 0 or cell[i] != cell[i - 1]] + [len(cell)]
    at = {cell[a]: slice(a, b) for a, b in zip(starts, starts[1:], strict=False)}
    root = {c: c for c in at}

    def find(c: tuple[int, int]) -> tuple[int, int]:
        while root[c] != c:
            root[c] = root[root[c]]
            c = root[c]
        return c

    blocks = []
    for (p, q), a in at.items():
        for other in [(p + i, q + j) for i in range(3) for j in range(-2, 3) if (i, j) >= (0, 0)]:
            b = at.get(other)
            if b is None:
                continue
            w = weights(x[a], y[a], x[b], y[b], radius, 0 if a == b else None)
            if w.any():
                blocks.append(((p, q), a, b, w))
                root[find((p, q))] = find(other)
    parts: dict[tuple[int, int], list] = {}
    for c, a, b, w in blocks:
        parts.setdefault(find(c), []).append((a, b, w))
    return sorted((_graph(ids, own) for own in parts.values()), key=lambda g: g.ids[0])


def _graph(ids: np.ndarray, blocks: list[tuple[slice, slice, np.ndarray]]) -> NearGraph:
    """A component from the blocks of all points: its slices are moved together."""
    moved, n, places = {}, 0, []
    for s in sorted({(s.start, s.stop) for a, b, _ in blocks for s in (a, b)}):
        moved[s] = slice(n, n + s[1] - s[0])
        n += s[1] - s[0]
        places.append(np.arange(*s))
    own = ids[np.concatenate(places)]
    order = np.empty(n, dtype=int)
    order[np.argsort(own)] = np.arange(n)
    none = np.zeros(0)
    g = NearGraph(np.sort(own), none, none, none, np.ones(n), order, [(moved[a.start, a.stop], moved[b.start, b.stop], w) for a, b, w in blocks])
    g.deg = g.sums(np.ones((n, 1)))[:, 0]
    return g


def near_labels(points: pd.DataFrame, radius: float, k: int, c2: float, steps: int | None, preset: Preset, seed: int = 0) -> pd.DataFrame:
    """As ``local_labels`` of the links between near points, for all components."""
    found = [labels_of(g, k, c2, steps, preset, seed) for g in near_graphs(points, radius)]
    return pd.concat(found, ignore_index=True) if found else pd.DataFrame({"id": [], "bits": [], "cluster": [], "group_rep": [], "margin": []})


def near_cluster(spark: SparkSession, points: DataFrame, radius: float, k: int = 1, c2: float = DEFAULT_C2, steps: int | None = None, preset: Preset = ROBUST, seed: int = 0, held_bytes: int = HELD_BYTES, scratch: Scratch | None = None) -> DataFrame:
    """The rows of ``wave_cluster`` over ``proximity(points, radius)``, from ``points(id, x, y)``.

    Counted first: where cells hold few points, or an id has several places, links are rows of an edge table as ever.
    """
    check_speed(c2)
    scratch = scratch or Scratch(spark, "near")
    cell = lambda c: F.floor(F.col(c) / (radius / 2))
    placed = scratch.save(points.where("id is not null and x is not null and y is not null").select(F.col("id").cast("long").alias("id"), F.col("x").cast("double").alias("x"), F.col("y").cast("double").alias("y"), cell("x").alias("cx"), cell("y").alias("cy")))
    own = scratch.save(placed.groupBy("cx", "cy").agg(F.count("*").alias("n")))
    side = F.explode(F.sequence(F.lit(-2), F.lit(2)))
    around = own.withColumn("i", side).withColumn("j", side).select((F.col("cx") + F.col("i")).alias("cx"), (F.col("cy") + F.col("j")).alias("cy"), "n")
    met = around.join(own.withColumnRenamed("n", "m"), ["cx", "cy"]).agg(F.count("*").alias("cells"), F.sum(F.col("n") * F.col("m")).alias("points")).first()
    distinct = placed.agg(F.count_distinct("id") == F.count("*")).first()[0]
    if not distinct or met["points"] < PAIRS_OF_POINTS * met["cells"]:
        return wave_cluster(spark, proximity(placed.select("id", "x", "y"), radius), k, c2, steps, preset, seed, scratch=scratch)
    if met["points"] * 4 <= held_bytes:  # each pair of cells is held once, in eight bytes
        return placed.groupBy(F.lit(0).alias("all")).applyInPandas(lambda part: near_labels(part, radius, k, c2, steps, preset, seed), LABELS)
    if steps is None or preset.parted or preset.frequencies != "peaks":
        raise ValueError("so many points run in tasks, which need given steps and read peaks")
    return NearParts(spark, placed, own, radius, scratch).labels(k, c2, steps, preset, seed)


#: A cell's points are dealt into parts of about so many.
PART = 1_024
PLACES = "p long, component long, ids array<long>, x array<double>, y array<double>, deg array<double>"
STATE = "p long, t int, u array<double>, v array<double>"


class NearParts:
    """Points beyond what one batch holds: cells in parts of a bounded size, and a stage of tasks for each step.

    A task makes the weights of its parts anew in each step. The places and values of all parts are broadcast while they are
    small, so that a step shuffles nothing; beyond that they are joined and dealt by part. Steps stay written until the sums are read.
    """

    def __init__(self, spark: SparkSession, placed: DataFrame, cells: DataFrame, radius: float, scratch: Scratch, part: int = PART) -> None:
        self.spark, self.radius, self.scratch = spark, radius, scratch
        chunks = cells.select("cx", "cy", F.ceil(F.col("n") / part).cast("int").alias("chunks"))
        dealt = placed.join(bounded_broadcast(chunks, cells.count()), ["cx", "cy"]).withColumn("ch", F.pmod(F.xxhash64("id"), "chunks"))
        rows = F.sort_array(F.collect_list(F.struct("id", "x", "y"))).alias("rows")
        found = scratch.save(dealt.groupBy("cx", "cy", "ch").agg(rows))
        numbered = scratch.save(ordered(found.select("cx", "cy", "ch"), ["cx", "cy", "ch"], scratch).withColumn("p", F.col("place").cast("long")))
        self.n_parts = numbered.count()
        self.tasks = min(self.n_parts, int(spark.conf.get("spark.sql.shuffle.partitions")))
        side = F.explode(F.sequence(F.lit(-2), F.lit(2)))
        around = numbered.select("p", "cx", "cy").withColumn("i", side).withColumn("j", side).select("p", (F.col("cx") + F.col("i")).alias("cx"), (F.col("cy") + F.col("j")).alias("cy"))
        met = around.join(numbered.select(F.col("p").alias("q"), "cx", "cy"), ["cx", "cy"]).select("p", "q")
        at = found.join(numbered, ["cx", "cy", "ch"]).select("p", F.col("rows.id").alias("ids"), F.col("rows.x").alias("x"), F.col("rows.y").alias("y"))
        self.places, self.pairs = scratch.save(at), scratch.save(met)
        self.n_points, self.n_pairs = placed.count(), self.pairs.count()
        self._link()

    def meeting(self, values: DataFrame, width: int) -> DataFrame:
        """(p, px, py, q, x, y, and what ``values(p, ..)`` has of q) for all near parts p and q, all rows of a p in one task."""
        few = self.n_pairs <= BROADCAST_ROWS and self.n_points * width * 8 <= BROADCAST_BYTES
        near = F.broadcast if few else (lambda df: df)
        all_parts = self.spark.range(0, self.n_parts, 1, self.tasks).withColumnRenamed("id", "p")
        here = self.places.select("p", F.col("x").alias("px"), F.col("y").alias("py"))
        there = self.places.select(F.col("p").alias("q"), "x", "y").join(near(values.withColumnRenamed("p", "q")), "q")
        rows = all_parts.join(near(here), "p").join(near(self.pairs), "p").join(near(there), "q")
        return rows if few else rows.repartition(self.tasks, "p")

    def _link(self) -> None:
        """Degrees, and components of parts: points of a cell are near each other, so parts are whole but for points without a link."""
        radius = self.radius

        def sums(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for batch in batches:
                out = []
                for r in batch.itertuples(index=False):
                    w = np.concatenate([weights(r.px[i : i + ROWS], r.py[i : i + ROWS], r.x, r.y, radius, i if r.p == r.q else None).sum(axis=1) for i in range(0, len(r.px), ROWS)])
                    if w.any():
                        out.append((r.p, r.q, w))
                yield pd.DataFrame(out, columns=["p", "q", "w"])

        def total(part: pd.DataFrame) -> pd.DataFrame:
            return pd.DataFrame({"p": part["p"].iloc[:1], "deg": [np.sum(part.sort_values("q")["w"].tolist(), axis=0)]})

        seen = self.scratch.save(self.meeting(self.places.select("p"), 4).mapInPandas(sums, "p long, q long, w array<double>"))
        whole = components(self.spark, self.scratch.save(seen.select(F.col("p").alias("src"), F.col("q").alias("dst"))), self.scratch).toDF("p", "component")
        deg = seen.groupBy("p").applyInPandas(total, "p long, deg array<double>")
        self.linked = self.scratch.save(self.places.join(whole, "p").join(deg, "p").select("p", "component", "ids", "x", "y", "deg"))

    def start(self, preset: Preset, seed: int) -> DataFrame:
        def first(ids: np.ndarray) -> np.ndarray:
            return np.column_stack([start_values(ids, seed + r) for r in range(preset.seeds)])

        def moments(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for batch in batches:
                yield pd.DataFrame([(r.component, [*(r.deg @ first(r.ids)), r.deg.sum()]) for r in batch.itertuples(index=False)], columns=["component", "m"])

        own = self.linked.select("component", "ids", "deg").mapInPandas(moments, "component long, m array<double>")
        of = own.groupBy("component").agg(F.array(*(F.sum(F.col("m")[r]) / F.sum(F.col("m")[preset.seeds]) for r in range(preset.seeds))).alias("mean"))

        def begin(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for batch in batches:
                u = [(first(r.ids) - (r.mean if preset.center else 0.0)).ravel() for r in batch.itertuples(index=False)]
                yield pd.DataFrame({"p": batch["p"], "t": 0, "u": u, "v": u})

        return self.linked.join(of, "component").select("p", "ids", "mean").mapInPandas(begin, STATE)

    def step(self, state: DataFrame, t: int, c2: float, seeds: int) -> DataFrame:
        radius = self.radius

        def go(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            total: dict[int, np.ndarray] = {}
            mine: dict[int, tuple[np.ndarray, ...]] = {}
            for batch in batches:
                for r in batch.itertuples(index=False):
                    u = r.u.reshape(-1, seeds)
                    if r.p == r.q:
                        mine[r.p] = u.copy(), r.v.reshape(-1, seeds).copy(), r.deg.copy()
                    out = total.setdefault(r.p, np.zeros((len(r.px), seeds)))
                    for i in range(0, len(r.px), ROWS):
                        out[i : i + ROWS] += weights(r.px[i : i + ROWS], r.py[i : i + ROWS], r.x, r.y, radius, i if r.p == r.q else None) @ u
            new = [(p, t, (2 * u - v - c2 * (u - total[p] / deg[:, None])).ravel(), u.ravel()) for p, (u, v, deg) in mine.items()]
            yield pd.DataFrame(new, columns=["p", "t", "u", "v"])

        held = state.select("p", "u", "v").join(self.linked.select("p", "deg"), "p")
        return self.meeting(held, 5 + 2 * seeds).mapInPandas(go, STATE)

    def labels(self, k: int, c2: float, steps: int, preset: Preset, seed: int) -> DataFrame:
        n, window, names = preset.seeds, window_values(preset.window, steps), []
        state = self.scratch.save(self.start(preset, seed))
        for t in range(1, steps + 1):
            names.append(f"near{uuid.uuid4().hex}")
            state = self.scratch.save(self.step(state, t, c2, n), names[-1])
        run = self.spark.read.schema(STATE).parquet(*(self.scratch.path(name) for name in names)).select("p", "t", "u")
        met = run.groupBy("p").cogroup(self.linked.groupBy("p"))

        def history(part: pd.DataFrame) -> np.ndarray:
            z = np.stack([u.reshape(-1, n) for u in part.sort_values("t")["u"]], axis=2)
            return (z if preset.center else z - z.mean(axis=2, keepdims=True)) * window

        def products(part: pd.DataFrame, own: pd.DataFrame) -> pd.DataFrame:
            """By bin: sums of y y' without and with conjugation, weighted by degree, from which power, turn and best mix of starts follow."""
            if part.empty:
                return pd.DataFrame({"component": [], "m": []})
            y = np.fft.rfft(history(part), axis=2).transpose(2, 0, 1)
            d = own["deg"].iloc[0][None, :, None]
            m = np.stack((np.matmul((y * d).transpose(0, 2, 1), y), np.matmul((y * d).transpose(0, 2, 1), y.conj())))
            return pd.DataFrame({"component": own["component"], "m": [np.stack((m.real, m.imag)).ravel()]})

        def added(part: pd.DataFrame) -> pd.DataFrame:
            return pd.DataFrame({"component": part["component"].iloc[:1], "m": [np.sum(part["m"].tolist(), axis=0)]})

        schema = "component long, m array<double>"
        mixes: dict[int, list[tuple[int, float, np.ndarray]]] = {}
        for row in met.applyInPandas(products, schema).groupBy("component").applyInPandas(added, schema).toLocalIterator():
            m = np.array(row["m"]).reshape(2, 2, -1, n, n)
            plain, crossed = m[0] + 1j * m[1]
            mixes[row["component"]] = []
            for b in find_peaks(np.trace(crossed.real, axis1=1, axis2=2), k, preset.prominence):
                turn = 0.5 * float(np.angle(np.trace(plain[b]))) if preset.align else 0.0
                gram = 0.5 * (crossed[b].real + (np.exp(-2j * turn) * plain[b]).real)  # of the real parts after the turn
                mixes[row["component"]].append((int(b), turn, np.linalg.eigh(gram)[1][:, -1]))

        def coefficients(part: pd.DataFrame, own: pd.DataFrame) -> pd.DataFrame:
            if part.empty:
                return pd.DataFrame({"component": [], "id": [], "deg": [], "coef": []})
            y, own = history(part), own.iloc[0]
            wave = lambda b, turn: np.exp(-2j * np.pi * b * np.arange(steps) / steps - 1j * turn)
            coef = [(y @ wave(b, turn)).real @ best for b, turn, best in mixes[own["component"]]]
            return pd.DataFrame({"component": own["component"], "id": own["ids"], "deg": own["deg"], "coef": list(np.array(coef).T) if coef else [[]] * len(own["ids"])})

        coef = self.scratch.save(met.applyInPandas(coefficients, "component long, id long, deg double, coef array<double>"))
        first = coef.groupBy("component").agg(F.min_by("coef", "id").alias("first"))
        rms = coef.select("component", "deg", F.posexplode("coef").alias("j", "c")).groupBy("component", "j").agg(F.sqrt(F.sum(F.col("deg") * F.col("c") ** 2) / F.sum("deg")).alias("s"))
        rms = rms.groupBy("component").agg(F.sort_array(F.collect_list(F.struct("j", "s"))).getField("s").alias("rms"))
        of = self.scratch.save(first.join(rms, "component", "left"))
        bits = F.zip_with("coef", "first", lambda c, f: ((c > 0) == (f > 0)).cast("int"))
        margin = F.coalesce(F.array_min(F.zip_with("coef", "rms", lambda c, s: F.abs(c) / F.greatest(s, F.lit(1e-300)))), F.lit(0.0))
        coded = coef.join(bounded_broadcast(of, self.n_parts), "component").select("component", "id", bits.alias("bits"), margin.alias("margin"))
        coded = self.scratch.save(coded.withColumn("cluster", F.aggregate(F.transform("bits", lambda b, j: b * F.pow(F.lit(2.0), j)), F.lit(0.0), lambda a, b: a + b).cast("long")))
        reps = coded.groupBy("component", "cluster").agg(F.min("id").alias("group_rep"))
        return coded.join(reps, ["component", "cluster"]).select("id", "bits", "cluster", "group_rep", "margin")
