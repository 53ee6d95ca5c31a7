"""Distributed estimation in a building: contaminant transport, consensus inside clusters, Kalman updates, fusion."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ripplegraph.operators.graph import degrees
from ripplegraph.operators.wave import laid_out, one_task
from ripplegraph.plans.scratch import Scratch


def flows(edges: DataFrame, rate: float = 1.0, inlet: int = 127, inflow: float = 2.0, outlets: tuple[int, ...] = (0, 7, 56, 63)) -> DataFrame:
    """(src, dst, f): air moved between rooms in proportion to link weight; -1 stands for outside."""
    spark = edges.sparkSession
    outside = [(-1, inlet, inflow), *((room, -1, inflow / len(outlets)) for room in outlets)]
    return edges.select("src", "dst", (F.col("w") * rate).alias("f")).unionByName(spark.createDataFrame(outside, "src long, dst long, f double"))


def rooms(spark: SparkSession, n: int = 128, sources: tuple[int, ...] = (9, 54, 73, 118), density: float = 1.0, volume: float = 50.0, generation: float = 5.0, removal: float = 0.01) -> DataFrame:
    """(id, c, mass, gen, rem): concentrations start at 0; four source rooms, two on each floor."""
    return spark.range(n).select("id", F.lit(0.0).alias("c"), F.lit(density * volume).alias("mass"), F.when(F.col("id").isin(*sources), generation).otherwise(0.0).alias("gen"), F.lit(removal).alias("rem"))


#: Stages of a step: share of the step to the next stage's point, and weight of the slope in the sum.
STAGES = {"euler": [(1.0, 1.0)], "rk4": [(0.5, 1 / 6), (0.5, 1 / 3), (1.0, 1 / 3), (0.0, 1 / 6)]}


def contaminant_run(spark: SparkSession, air: DataFrame, state: DataFrame, steps: int, dt: float = 0.1, scratch: Scratch | None = None, unroll: int = 8, method: str = "euler") -> DataFrame:
    """``steps`` of mass * dc/dt = inflow - outflow + gen - rem * c, by Euler or fourth-order steps; one join and one sum a stage."""
    scratch = scratch or Scratch(spark, "contaminant")
    out = air.groupBy(F.col("src").alias("id")).agg(F.sum("f").alias("leaves"))
    own = state.select("id", F.col("id").alias("to")).join(out, "id", "left").select("id", "to", (-F.coalesce("leaves", F.lit(0.0))).alias("f"), F.lit(True).alias("own"))
    rows, few = laid_out(own.unionByName(air.where("src >= 0 and dst >= 0").select(F.col("src").alias("id"), F.col("dst").alias("to"), "f", F.lit(False).alias("own"))), scratch, "id")
    state = one_task(state.withColumns({"y": F.col("c"), "sum": F.lit(0.0)}), few)
    stages = STAGES[method]
    done = 0
    for t in range(1, steps + 1):
        for i, (share, weight) in enumerate(stages):
            mine = lambda c: F.max(F.when(F.col("own"), F.col(c))).alias(c)
            moved = rows.join(state, "id").groupBy("to").agg(F.sum(F.col("f") * F.col("y")).alias("net"), *(mine(c) for c in ("c", "y", "sum", "mass", "gen", "rem")))
            slope = (F.col("net") + F.col("gen") - F.col("rem") * F.col("y")) / F.col("mass")
            total = F.col("sum") + slope * weight
            if i + 1 < len(stages):
                new = {"c": F.col("c"), "y": F.col("c") + slope * (dt * share), "sum": total}
            else:
                new = {"c": F.col("c") + total * dt, "y": F.col("c") + total * dt, "sum": F.lit(0.0)}
            state = moved.select(F.col("to").alias("id"), *(x.alias(c) for c, x in new.items()), "mass", "gen", "rem")
            done += 1
            if done % unroll == 0 and (t < steps or i + 1 < len(stages)):
                state = one_task(scratch.save(state), few)
    return scratch.save(state.drop("y", "sum"))


def within(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """Links inside clusters; ``labels(id, cluster)``."""
    return edges.join(labels.toDF("src", "a"), "src").join(labels.toDF("dst", "b"), "dst").where("a = b").select("src", "dst", "w")


def consensus(spark: SparkSession, values: DataFrame, edges: DataFrame, rounds: int, scratch: Scratch | None = None, unroll: int = 8) -> DataFrame:
    """(id, x) after ``rounds`` of averaging with the neighbours; Metropolis weights, so the plain mean is the limit.

    ``edges`` holds the links that may talk (see ``within``); nodes without any keep their value.
    """
    scratch = scratch or Scratch(spark, "consensus")
    count = edges.groupBy("src").agg(F.count("*").alias("n"))
    pairs = edges.join(count, "src").join(count.toDF("dst", "m"), "dst").select("src", "dst", (1 / (1 + F.greatest("n", "m"))).alias("p"))
    loops = values.select(F.col("id").alias("src")).join(pairs.groupBy("src").agg(F.sum("p").alias("out")), "src", "left").select("src", F.col("src").alias("dst"), (1 - F.coalesce("out", F.lit(0.0))).alias("p"))
    rows, few = laid_out(pairs.unionByName(loops), scratch)
    values = one_task(values, few)
    for t in range(1, rounds + 1):
        values = rows.join(values, rows["dst"] == values["id"]).groupBy("src").agg(F.sum(F.col("p") * F.col("x")).alias("x")).withColumnRenamed("src", "id")
        if t % unroll == 0 and t < rounds:
            values = one_task(scratch.save(values), few)
    return values


def fuse(estimates: DataFrame) -> DataFrame:
    """(x): mean over clusters of ``(id, cluster, x)``, weighted by their sizes."""
    return estimates.groupBy("cluster").agg(F.avg("x").alias("mean"), F.count("*").alias("n")).agg((F.sum(F.col("mean") * F.col("n")) / F.sum("n")).alias("x"))


def floor_partition(nodes: DataFrame) -> DataFrame:
    """Two clusters by design: the floors."""
    return nodes.select("id", F.floor(F.col("id") / 64).cast("long").alias("cluster"))


def iterations_to_tol(distances: DataFrame, tol: float) -> DataFrame:
    """(rounds): the first of ``(rounds, rms)`` within ``tol``."""
    return distances.where(F.col("rms") <= tol).agg(F.min("rounds").alias("rounds"))


def consensus_errors(values: DataFrame, edges: DataFrame, labels: DataFrame, rounds: list[int], max_rooms: int = 1_000) -> DataFrame:
    """(rounds, rms): distance of all nodes from their cluster's mean after so many rounds, as a batch of a checked size.

    ``values(id, x)`` and ``labels(id, cluster)`` of nodes 0 .. n-1; only links inside clusters talk.
    """
    n = labels.count()
    if n > max_rooms:
        raise ValueError(f"{n} nodes are more than the {max_rooms} of one batch")

    def curve(part: pd.DataFrame) -> pd.DataFrame:
        own = part[part["dst"] < 0].sort_values("src")
        x, group = own["w"].to_numpy(), own["cluster"].to_numpy()
        links = part[part["dst"] >= 0]
        a, b = links["src"].to_numpy(), links["dst"].to_numpy()
        same = group[a] == group[b]
        mix = metropolis(a[same], b[same], n)
        mean = (np.bincount(group, x) / np.maximum(np.bincount(group), 1))[group]
        out, done, now = [], 0, x
        for r in sorted(rounds):
            now, done = np.linalg.matrix_power(mix, r - done) @ now, r
            out.append((r, float(np.sqrt(((now - mean) ** 2).mean()))))
        return pd.DataFrame(out, columns=["rounds", "rms"])

    own = values.join(labels, "id").select(F.col("id").alias("src"), F.lit(-1).cast("long").alias("dst"), F.col("x").alias("w"), F.col("cluster").cast("long").alias("cluster"))
    both = own.unionByName(edges.select("src", "dst", "w", F.lit(-1).cast("long").alias("cluster")))
    return both.groupBy(F.lit(0).alias("all")).applyInPandas(curve, "rounds int, rms double")


@dataclass(frozen=True)
class Filter:
    """Constants of the estimation experiment."""

    updates: int = 100
    rounds: int = 10
    dt: float = 0.1
    noise: float = 0.5
    process: float = 0.02
    seed: int = 7


def metropolis(src: np.ndarray, dst: np.ndarray, n: int) -> np.ndarray:
    m = np.zeros((n, n))
    count = np.bincount(src, minlength=n)
    m[src, dst] = 1 / (1 + np.maximum(count[src], count[dst]))
    m[np.arange(n), np.arange(n)] = 1 - m.sum(axis=1)
    return m


def kalman_experiment(edges: pd.DataFrame, air: pd.DataFrame, clusters: np.ndarray, f: Filter = Filter(), sources: tuple[int, ...] = (9, 54, 73, 118)) -> pd.DataFrame:
    """(update, id, truth, estimate, sigma): every sensor estimates all rooms of its cluster.

    A sensor measures its own room; between updates the sensors of a cluster average estimates and
    information matrices for a number of rounds. Rooms outside the cluster are boundary noise.
    """
    n = len(clusters)
    rng = np.random.default_rng(f.seed)
    move = np.zeros((n, n))
    inner = air[(air["src"] >= 0) & (air["dst"] >= 0)]
    np.add.at(move, (inner["dst"].to_numpy(), inner["src"].to_numpy()), inner["f"].to_numpy())
    leaves = np.zeros(n)
    out = air[air["src"] >= 0]
    np.add.at(leaves, out["src"].to_numpy(), out["f"].to_numpy())
    mass, removal = 50.0, 0.01
    a = np.eye(n) + f.dt / mass * (move - np.diag(leaves) - removal * np.eye(n))
    gen = np.zeros(n)
    gen[list(sources)] = 5.0 * f.dt / mass
    same = clusters[edges["src"].to_numpy()] == clusters[edges["dst"].to_numpy()]
    mix = np.linalg.matrix_power(metropolis(edges["src"].to_numpy()[same], edges["dst"].to_numpy()[same], n), f.rounds)
    truth = np.zeros(n)
    groups = [np.flatnonzero(clusters == c) for c in np.unique(clusters)]
    x = {c: np.zeros((len(g), len(g))) for c, g in enumerate(groups)}  # sensor by room
    info = {c: np.repeat(np.eye(len(g))[None] * 4.0, len(g), axis=0) for c, g in enumerate(groups)}
    rows = []
    for update in range(1, f.updates + 1):
        truth = a @ truth + gen + rng.normal(0, f.process, n)
        seen = truth + rng.normal(0, f.noise, n)
        for c, g in enumerate(groups):
            k = len(g)
            own, w = a[np.ix_(g, g)], mix[np.ix_(g, g)]
            x[c] = x[c] @ own.T + gen[g]
            cov = own @ np.linalg.inv(info[c]) @ own.T + np.eye(k) * f.process**2 * 4
            info[c] = np.linalg.inv(cov)
            vec = np.einsum("sij,sj->si", info[c], x[c])
            gain = k / f.noise**2  # every sensor adds its own reading, means of all of them are shared
            info[c][np.arange(k), np.arange(k), np.arange(k)] += gain
            vec[np.arange(k), np.arange(k)] += gain * seen[g]
            info[c], vec = np.einsum("st,tij->sij", w, info[c]), w @ vec
            x[c] = np.linalg.solve(info[c], vec[:, :, None])[:, :, 0]
            sigma = np.sqrt(np.array([np.linalg.inv(info[c][s])[s, s] for s in range(k)]))
            rows.append(pd.DataFrame({"update": update, "id": g, "truth": truth[g], "estimate": x[c][np.arange(k), np.arange(k)], "sigma": sigma, "rms": np.sqrt(((x[c] - truth[g]) ** 2).mean(axis=1))}))
    return pd.concat(rows, ignore_index=True)


def experiment(edges: DataFrame, air: DataFrame, labels: DataFrame, f: Filter = Filter(), max_rooms: int = 1_000) -> DataFrame:
    """The experiment as a batch of a checked size: ``labels(id, cluster)`` for rooms 0 .. n-1."""
    n = labels.count()
    if n > max_rooms:
        raise ValueError(f"{n} rooms are more than the {max_rooms} of one building")

    def rows(part: pd.DataFrame) -> pd.DataFrame:
        pick = lambda kind: part[part["kind"] == kind]
        own = pick(2).sort_values("src")
        return kalman_experiment(pick(0).sort_values(["src", "dst"]), pick(1).rename(columns={"w": "f"}).sort_values(["src", "dst"]), own["dst"].to_numpy(), f)

    parts = edges.select(F.lit(0).alias("kind"), "src", "dst", "w").unionByName(air.select(F.lit(1).alias("kind"), "src", "dst", F.col("f").alias("w"))).unionByName(labels.select(F.lit(2).alias("kind"), F.col("id").alias("src"), F.col("cluster").alias("dst"), F.lit(0.0).alias("w")))
    return parts.groupBy(F.lit(0).alias("all")).applyInPandas(rows, "update int, id long, truth double, estimate double, sigma double, rms double")


def report(results: DataFrame, room: int) -> DataFrame:
    """(rmse, covered, rms_cluster): error in one room, share of updates within three sigma, error over the cluster's rooms."""
    off = F.col("estimate") - F.col("truth")
    return results.where(F.col("id") == room).agg(F.sqrt(F.avg(off * off)).alias("rmse"), F.avg(F.when(F.abs(off) <= 3 * F.col("sigma"), 1.0).otherwise(0.0)).alias("covered"), F.avg("rms").alias("rms_cluster"))


def drift(old: DataFrame, new: DataFrame) -> DataFrame:
    """(drift): share of weight that changed between two edge tables."""
    both = old.toDF("src", "dst", "x").join(new.toDF("src", "dst", "y"), ["src", "dst"], "full")
    x, y = F.coalesce("x", F.lit(0.0)), F.coalesce("y", F.lit(0.0))
    return both.agg((F.sum(F.abs(x - y)) / F.greatest(F.sum(x + y), F.lit(1e-300))).alias("drift"))


def maybe_recluster(old: DataFrame, new: DataFrame, labels: DataFrame, cluster, limit: float = 0.1) -> DataFrame:
    """``cluster(new)`` if the drift passes the limit, else the labels as they are."""
    return cluster(new) if drift(old, new).first()["drift"] > limit else labels


def isolated(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """Nodes without links."""
    return nodes.join(degrees(edges), "id", "left_anti")
