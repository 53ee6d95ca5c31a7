"""Discretised waves on a graph, as one join and one aggregation a step.

A node's next value is ``2 cur - prev - c2 (cur - sum of p cur over its neighbours)``. The walk table carries a
row from each node to itself, so a step reads the state once: own terms and messages meet in one sum. Plans
of several steps therefore grow linearly and end in a written table, which cuts lineage.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ripplegraph.functions.bounds import DEFAULT_C2, check_speed
from ripplegraph.operators.graph import walk_weights
from ripplegraph.plans.scratch import BROADCAST_ROWS, Scratch

_M = 2147483647


def start_value(node: Column | str, seed: int, dist: str = "uniform") -> Column:
    """Reproducible start from a node's id and a seed, by integer arithmetic that any engine repeats."""
    own = F.pmod(F.col(node) if isinstance(node, str) else node, F.lit(_M))
    h = F.pmod(own * 48271 + F.lit(seed).cast("long") * 16807 + 12345, F.lit(_M))
    unit = F.pmod(F.pmod(h * h, F.lit(_M)) + own * 7919, F.lit(_M)) / F.lit(float(_M))
    if dist == "rademacher":
        return F.when(unit < 0.5, F.lit(-1.0)).otherwise(F.lit(1.0))
    if dist == "normal":
        again = F.pmod(F.pmod((h + 1) * (h + 1), F.lit(_M)) + own * 104729, F.lit(_M)) / F.lit(float(_M))
        return F.sqrt(-2 * F.log(F.greatest(unit, F.lit(1e-12)))) * F.cos(2 * math.pi * again)
    return unit


def initial_state(nodes: DataFrame, n_seeds: int = 1, center: str = "none", dist: str = "uniform", values: Column | None = None, low: float = 0.0, high: float = 1.0, seed: int = 0) -> DataFrame:
    """(id, deg, u0.., v0..): current and previous values, equal at the start; ``center`` takes the degree-weighted mean off."""
    start = [values if values is not None else F.lit(low) + start_value("id", seed + r, dist) * (high - low) for r in range(n_seeds)]
    state = nodes.select("id", "deg", *(x.alias(f"u{r}") for r, x in enumerate(start)))
    if center == "degree":
        mean = state.agg(*((F.sum(F.col("deg") * F.col(f"u{r}")) / F.sum("deg")).alias(f"m{r}") for r in range(n_seeds)))
        state = state.crossJoin(F.broadcast(mean)).select("id", "deg", *((F.col(f"u{r}") - F.col(f"m{r}")).alias(f"u{r}") for r in range(n_seeds)))
    return state.select("id", "deg", *(f"u{r}" for r in range(n_seeds)), *(F.col(f"u{r}").alias(f"v{r}") for r in range(n_seeds)))


def with_own_rows(walk: DataFrame) -> DataFrame:
    """(src, dst, p, own): walk rows, and a row from each node to itself that carries its own terms."""
    loops = walk.select(F.col("src").alias("src"), F.col("src").alias("dst"), F.lit(0.0).alias("p"), F.lit(True).alias("own")).distinct()
    return walk.select("src", "dst", "p", F.lit(False).alias("own")).unionByName(loops)


def laid_out(rows: DataFrame, scratch: Scratch, column: str = "dst") -> tuple[DataFrame, bool]:
    """``rows`` as every step reads them, and whether they are few: few rows are broadcast, others bucketed by ``column``.

    A step's sums are dealt by the node they belong to, which is the key of the next join, so over a bucketed
    table a step shuffles its messages once and never the edges.
    """
    saved = scratch.save(rows)
    if saved.count() <= BROADCAST_ROWS:
        return F.broadcast(saved), True
    return scratch.bucketed(saved, column), False


def one_task(state: DataFrame, few: bool) -> DataFrame:
    """The state of a graph of few rows in one task, where steps need no exchange at all."""
    return state.coalesce(1) if few else state


def _seeds(state: DataFrame) -> int:
    return sum(1 for c in state.columns if c[0] == "u" and c[1:].isdigit())


def step(rows: DataFrame, state: DataFrame, own: Column | float, before: float, message: float, carried: dict[str, Column] | None = None) -> DataFrame:
    """next = own * cur - before * prev + message * sum(p * cur); ``carried`` columns see cur and go on with the node.

    ``rows`` comes from ``with_own_rows``. Waves use (2 - c2, 1, c2), heat and walks (1 - k, 0, k).
    """
    n = _seeds(state)
    keep = {c: F.col(c) for c in state.columns if c not in {"id", *(f"u{r}" for r in range(n)), *(f"v{r}" for r in range(n))}}
    keep |= carried or {}
    met = rows.join(state, rows["dst"] == state["id"])
    mine = lambda x: F.max(F.when(F.col("own"), x))
    total = lambda r: F.sum(F.when(F.col("own"), F.col(f"u{r}") * own - F.col(f"v{r}") * before).otherwise(F.col("p") * F.col(f"u{r}") * message))
    out = met.groupBy("src").agg(*(total(r).alias(f"u{r}") for r in range(n)), *(mine(F.col(f"u{r}")).alias(f"v{r}") for r in range(n)), *(mine(x).alias(c) for c, x in keep.items()))
    return out.withColumnRenamed("src", "id")


def run(spark: SparkSession, edges: DataFrame, state: DataFrame, steps: int, c2: float = DEFAULT_C2, scratch: Scratch | None = None, unroll: int = 8, history: bool = False, filters: list[float] | None = None, window: str = "hann", total: int | None = None, checked: bool = True, form: str = "walk", batch: bool = True) -> DataFrame:
    """State after ``steps`` steps.

    A graph of few walk rows (counted, see ``laid_out``) takes all its steps in one Arrow batch unless ``batch`` is
    off; larger graphs take them as joins. The numbers are the same but for the order of sums.

    ``history`` keeps all values of a node in arrays ``series0..`` (small graphs). ``filters`` are frequencies
    for which windowed sums of cos and sin are kept with each node instead (``re{j}_{r}``, ``im{j}_{r}``); memory
    per node then does not depend on the number of steps.
    """
    if checked:
        check_speed(c2)
    scratch = scratch or Scratch(spark, "wave")
    rows, few = laid_out(with_own_rows(walk_weights(edges, form)), scratch)
    if few and batch:
        return scratch.save(in_batch(rows, state, steps, c2, history, filters, window, total or steps)[0])
    state = one_task(state, few)
    n = _seeds(state)
    span = total or steps
    if history:
        state = state.withColumns({f"series{r}": F.array().cast("array<double>") for r in range(n)})
    for j in range(len(filters or [])):
        state = state.withColumns({f"{part}{j}_{r}": F.lit(0.0) for part in ("re", "im") for r in range(n)})
    if filters:
        state = state.withColumn("t", F.lit(0))  # a column, so that every block of steps has the same code
        state = state.withColumns({f"total{r}": F.lit(0.0) for r in range(n)})
    for t in range(1, steps + 1):
        state = step(rows, state, 2 - c2, 1.0, c2)
        new: dict[str, Column] = {f"series{r}": F.concat(f"series{r}", F.array(f"u{r}")) for r in range(n)} if history else {}
        if filters:
            state = state.withColumns({"t": F.col("t") + 1, **{f"total{r}": F.col(f"total{r}") + F.col(f"u{r}") for r in range(n)}})
            h = window_column(window, F.col("t"), span)
            for j, omega in enumerate(filters):
                wave = F.struct((h * F.cos(F.col("t") * omega)).alias("c"), (h * F.sin(F.col("t") * omega)).alias("s"))
                state = state.withColumn("wave", wave)
                new = {f"re{j}_{r}": F.col(f"re{j}_{r}") + F.col(f"u{r}") * F.col("wave.c") for r in range(n)}
                new |= {f"im{j}_{r}": F.col(f"im{j}_{r}") - F.col(f"u{r}") * F.col("wave.s") for r in range(n)}
                state = state.withColumns(new).drop("wave")
            new = {f"series{r}": F.concat(f"series{r}", F.array(f"u{r}")) for r in range(n)} if history else {}
        state = state.withColumns(new) if new else state
        if t % unroll == 0 and t < steps:
            state = one_task(scratch.save(state), few)
    return scratch.save(state)


def detrended_sums(done: DataFrame, omegas: list[float], steps: int, window: str, n: int) -> DataFrame:
    """Filter sums as if each node's mean over the run had been taken off before."""
    new = {}
    for j, omega in enumerate(omegas):
        c = sum(window_value(window, t, steps) * math.cos(omega * t) for t in range(1, steps + 1))
        s = sum(window_value(window, t, steps) * math.sin(omega * t) for t in range(1, steps + 1))
        for r in range(n):
            mean = F.col(f"total{r}") / steps
            new |= {f"re{j}_{r}": F.col(f"re{j}_{r}") - mean * c, f"im{j}_{r}": F.col(f"im{j}_{r}") + mean * s}
    return done.withColumns(new) if new else done


def window_value(kind: str, t: int, steps: int) -> float:
    x = 2 * math.pi * (t - 0.5) / steps
    return {"rect": 1.0, "hann": 0.5 - 0.5 * math.cos(x), "hamming": 0.54 - 0.46 * math.cos(x), "blackman": 0.42 - 0.5 * math.cos(x) + 0.08 * math.cos(2 * x)}[kind]


def window_column(kind: str, t: Column, steps: int) -> Column:
    x = (t - 0.5) * (2 * math.pi / steps)
    return {"rect": F.lit(1.0), "hann": 0.5 - 0.5 * F.cos(x), "hamming": 0.54 - 0.46 * F.cos(x), "blackman": 0.42 - 0.5 * F.cos(x) + 0.08 * F.cos(2 * x)}[kind]


def long_history(state: DataFrame) -> DataFrame:
    """(id, t, u) of the first start of a run with history."""
    return state.select("id", F.posexplode("series0").alias("t", "u")).withColumn("t", F.col("t") + 1)


def probes(nodes: DataFrame, count: int) -> DataFrame:
    """A fixed number of nodes with the smallest hashes: frequencies are the same in all nodes."""
    return nodes.orderBy(F.xxhash64("id"), "id").limit(count)


def probe_series(spark: SparkSession, edges: DataFrame, state: DataFrame, steps: int, count: int = 64, c2: float = DEFAULT_C2, scratch: Scratch | None = None, unroll: int = 8) -> DataFrame:
    """(id, t, u0..) of ``count`` probe nodes over a run; nothing else is kept of the steps."""
    scratch = scratch or Scratch(spark, "probes")
    return scratch.save(Probes(spark, edges, state, count, c2, scratch, unroll).go(steps))


def in_batch(rows: DataFrame, state: DataFrame, steps: int, c2: float, history: bool = False, filters: list[float] | None = None, window: str = "hann", span: int = 0) -> tuple[DataFrame, str]:
    """All steps of a graph of few rows in one batch: the columns that ``run`` gives, and their schema."""
    n = _seeds(state)
    now, before = [f"u{r}" for r in range(n)], [f"v{r}" for r in range(n)]
    series = [f"series{r}" for r in range(n)] if history else []
    sums = [f"{part}{j}_{r}" for j in range(len(filters or [])) for part in ("re", "im") for r in range(n)]
    totals = [f"total{r}" for r in range(n)] if filters else []
    schema = ", ".join(["id long", "deg double", *(f"{c} double" for c in now + before), *(f"{c} array<double>" for c in series), *(f"{c} double" for c in totals + sums)])

    def go(links: pd.DataFrame, own: pd.DataFrame) -> pd.DataFrame:
        own = own.sort_values("id")
        ids = own["id"].to_numpy()
        links = links[~links["own"]].sort_values(["src", "dst"])
        a, b, p = np.searchsorted(ids, links["src"].to_numpy()), np.searchsorted(ids, links["dst"].to_numpy()), links["p"].to_numpy()
        u, v = own[now].to_numpy(float), own[before].to_numpy(float)
        seen = np.empty((len(ids), n, steps if history else 0))
        kept = np.zeros((len(ids), n, len(filters or [])), dtype=complex)
        total = np.zeros_like(u)
        for t in range(1, steps + 1):
            mean = np.column_stack([np.bincount(a, p * u[b, r], len(ids)) for r in range(n)])
            u, v = (2 - c2) * u - v + c2 * mean, u
            if history:
                seen[:, :, t - 1] = u
            if filters:
                total = total + u
                kept += u[:, :, None] * (window_value(window, t, span) * np.exp(-1j * np.array(filters) * t))
        out = {"id": ids, "deg": own["deg"].to_numpy(), **{c: u[:, r] for r, c in enumerate(now)}, **{c: v[:, r] for r, c in enumerate(before)}, **{c: list(seen[:, r]) for r, c in enumerate(series)}}
        out |= {c: total[:, r] for r, c in enumerate(totals)}
        out |= {f"{part}{j}_{r}": (kept.real if part == "re" else kept.imag)[:, r, j] for j in range(len(filters or [])) for part in ("re", "im") for r in range(n)}
        return pd.DataFrame(out)

    key = F.lit(0).alias("all")
    return rows.groupBy(key).cogroup(state.select("id", "deg", *now, *before).groupBy(key)).applyInPandas(go, schema), schema


class Probes:
    """A run whose probes are read span by span, so that it can go on where it stopped."""

    def __init__(self, spark: SparkSession, edges: DataFrame, state: DataFrame, count: int = 64, c2: float = DEFAULT_C2, scratch: Scratch | None = None, unroll: int = 8) -> None:
        check_speed(c2)
        self.scratch, self.state, self.c2, self.unroll, self.t = scratch or Scratch(spark, "probes"), state, c2, unroll, 0
        self.rows, self.few = laid_out(with_own_rows(walk_weights(edges)), self.scratch)
        self.chosen = F.broadcast(self.scratch.save(probes(state.select("id", "deg"), count)))

    def go(self, steps: int) -> DataFrame:
        """(id, t, u0..) of the probes over the next ``steps`` steps."""
        n = _seeds(self.state)
        path = self.scratch.path(f"seen{self.t}")
        if self.few:
            state = self.scratch.save(in_batch(self.rows, self.state, steps, self.c2, history=True)[0])
            each = F.posexplode(F.arrays_zip(*(F.col(f"series{r}").alias(f"u{r}") for r in range(n)))).alias("t", "x")
            seen = state.join(self.chosen.select("id"), "id").select("id", each).select("id", (F.col("t") + (self.t + 1)).alias("t"), *(F.col(f"x.u{r}") for r in range(n)))
            self.state = state.drop(*(f"series{r}" for r in range(n)))
            self.t += steps
            return self.scratch.save(seen)
        done = 0
        while done < steps:
            block = min(self.unroll, steps - done)
            seen: list[str] = []
            state = one_task(self.state, self.few)
            for k in range(1, block + 1):
                state = step(self.rows, state, 2 - self.c2, 1.0, self.c2)
                if k < block:
                    state = state.withColumns({f"at{k}_{r}": F.col(f"u{r}") for r in range(n)})
                    seen += [f"at{k}_{r}" for r in range(n)]
            state = self.scratch.save(state)
            each = [F.struct(F.lit(self.t + k).alias("t"), *(F.col(f"at{k}_{r}" if k < block else f"u{r}").alias(f"u{r}") for r in range(n))) for k in range(1, block + 1)]
            state.join(self.chosen.select("id"), "id").select("id", F.inline(F.array(*each))).coalesce(1).write.mode("append").parquet(path)  # probes times steps of a block
            self.state = state.drop(*seen)
            self.t += block
            done += block
        return self.scratch.spark.read.schema(f"id long, t int, {', '.join(f'u{r} double' for r in range(n))}").parquet(path)


def run_blocks(spark: SparkSession, edges: DataFrame, state: DataFrame, steps: int, q: int = 4, c2: float = DEFAULT_C2, block_rows: int = 500_000, scratch: Scratch | None = None) -> DataFrame:
    """The same as ``run`` by blocks of nodes that carry a halo of ``q`` hops and take ``q`` steps alone.

    A node's value after q steps depends on nodes within q hops only. The state is dealt to blocks and halos once
    every q steps instead of every step; that pays where halos are small (lines, rings, grids, meshes). Blocks
    are ranges of ids of about ``block_rows`` walk rows, so that neighbours in id order share one.
    """
    check_speed(c2)
    scratch = scratch or Scratch(spark, "blocks")
    rows = scratch.save(walk_weights(edges).select("src", "dst", "p"))
    n_blocks = max(1, -(-rows.count() // block_rows))
    bounds = rows.select(F.percentile_approx("src", [i / n_blocks for i in range(1, n_blocks)], 10_000)).first()[0] if n_blocks > 1 else []
    block = F.size(F.filter(F.array(*(F.lit(int(b)) for b in bounds)), lambda b: b < F.col("id"))) if bounds else F.lit(0)
    member = scratch.save(state.select(block.alias("block"), "id", F.lit(0).alias("hop")))
    for hop in range(1, q + 1):
        reached = member.where(F.col("hop") == hop - 1).join(rows, F.col("id") == rows["src"]).select("block", F.col("dst").alias("id"), F.lit(hop).alias("hop"))
        member = scratch.save(member.unionByName(reached).groupBy("block", "id").agg(F.min("hop").alias("hop")))
    inner = scratch.save(member.where(F.col("hop") < q).join(rows, F.col("id") == rows["src"]).select("block", "src", "dst", "p"))
    n = _seeds(state)
    now, before = [f"u{r}" for r in range(n)], [f"v{r}" for r in range(n)]
    done = 0
    while done < steps:
        take = min(q, steps - done)

        def go(links: pd.DataFrame, own: pd.DataFrame) -> pd.DataFrame:
            ids = np.sort(own["id"].to_numpy())
            own = own.set_index("id").loc[ids]
            a, b, p = np.searchsorted(ids, links["src"].to_numpy()), np.searchsorted(ids, links["dst"].to_numpy()), links["p"].to_numpy()
            order = np.lexsort((b, a))
            a, b, p = a[order], b[order], p[order]
            u, v = own[now].to_numpy(float), own[before].to_numpy(float)
            for _ in range(take):  # noqa: B023
                mean = np.column_stack([np.bincount(a, p * u[b, r], len(ids)) for r in range(n)])
                u, v = 2 * u - v - c2 * (u - mean), u
            out = pd.DataFrame({"id": ids, "deg": own["deg"].to_numpy(), **{c: u[:, r] for r, c in enumerate(now)}, **{c: v[:, r] for r, c in enumerate(before)}})
            return out[(own["hop"] == 0).to_numpy()]

        met = member.join(state.select("id", "deg", *now, *before), "id")
        schema = ", ".join(["id long", "deg double", *(f"{c} double" for c in now + before)])
        state = scratch.save(inner.groupBy("block").cogroup(met.groupBy("block")).applyInPandas(go, schema))
        done += take
    return state
