"""Registered queries of measured experiments: spectra read as numbers, rounds to converge, estimation, search."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ripplegraph.functions import bounds
from ripplegraph.operators import baselines, cluster, estimation, joins, metrics, search, spectrum, wave
from ripplegraph.operators.graph import nodes_of, symmetrize
from ripplegraph.plans.ordered import ordered
from ripplegraph.plans.scratch import Scratch
from ripplegraph.queries import C2, Query, _agents, _belief, _five, _history, _readings, _reps, _trade, rounded
from ripplegraph.sources import builders
from ripplegraph.sources.tables import table

#: Ring sizes and numbers of steps of the measured comparison of waves and walks.
RINGS = (8, 16, 32, 64)
SPANS = (16, 32, 64, 128, 256, 512, 1024)
ONE = cluster.Preset(seeds=1)


# --- waves and spectra ----------------------------------------------------------------------------


def wave_given_start(spark, sf):
    """Ten steps from a start that the user gives: a column over the nodes."""
    scratch, edges = _trade(spark, sf)
    state = wave.run(spark, edges, wave.initial_state(nodes_of(edges), values=F.col("id") / 25.0), 10, C2, scratch)
    return rounded(state.select("id", "u0"))


def ring_wave(spark, sf):
    scratch = Scratch(spark, "ring")
    edges = scratch.save(builders.ring(spark, 32))
    return rounded(wave.run(spark, edges, wave.initial_state(nodes_of(edges)), 24, C2, scratch).select("id", "u0"))


def day_ring_wave_blocks(spark, sf):
    """Steps by blocks of days with halos of four hops; equals the plain run."""
    scratch = Scratch(spark, "blocks")
    edges = scratch.save(builders.day_ring(spark, sf))
    return rounded(wave.run_blocks(spark, edges, wave.initial_state(nodes_of(edges)), 10, 4, C2, 600, scratch).select("id", "u0"))


def fft_trade(spark, sf):
    """Whole transforms of node histories, all bins."""
    _, state = _history(spark, sf, 32)
    return rounded(spectrum.fft(state, "rect", detrend=False).select("id", "bin", "re", "im"))


def windowed_dft_kinds(spark, sf):
    _, state = _history(spark, sf, 32)
    history = wave.long_history(state)
    parts = [spectrum.dft(history, [2, 8], 32, kind).withColumn("kind", F.lit(kind)) for kind in ("hamming", "blackman")]
    return rounded(parts[0].unionByName(parts[1]))


def detrended_trade(spark, sf):
    """Histories without their means over time, without the weighted mean of each step, and as differences."""
    nodes, state = _history(spark, sf, 12)
    history = wave.long_history(state).join(nodes, "id")
    parts = [spectrum.detrended(history, how).select(F.lit(how).alias("how"), "id", "t", "u") for how in ("mean", "degree", "difference")]
    return rounded(parts[0].unionByName(parts[1]).unionByName(parts[2]))


def _region_power(spark: SparkSession, sf: str, steps: int = 200) -> tuple[DataFrame, DataFrame]:
    """(nodes, spectra (id, bin, power)) of the region chain's wave from one centred start."""
    scratch = Scratch(spark, "power")
    edges = scratch.save(builders.region_chain(spark, sf))
    nodes = scratch.save(nodes_of(edges))
    state = wave.run(spark, edges, wave.initial_state(nodes, 1, "degree"), steps, C2, scratch, history=True)
    return nodes, scratch.save(spectrum.fft(state, "hann", detrend=False).select("id", "bin", "power"))


def _region_peaks(spark: SparkSession, sf: str) -> DataFrame:
    nodes, power = _region_power(spark, sf)
    pooled = power.join(nodes, "id").groupBy("bin").agg(F.sum(F.col("deg") * F.col("power")).alias("power"))
    return spectrum.peaks(pooled, 4, 200)


def peaks_region(spark, sf):
    """The four lowest peaks of the pooled spectrum: frequencies, and the eigenvalues that they stand for."""
    return rounded(_region_peaks(spark, sf).select("j", "bin", "omega", "lam"))


def local_peaks_region(spark, sf):
    """Each nation's own two lowest peaks."""
    _, power = _region_power(spark, sf)
    return rounded(spectrum.peaks(power, 2, 200, by="id").select("id", "j", "bin", "lam"))


def choose_k_region(spark, sf):
    return _region_peaks(spark, sf).transform(spectrum.choose_k)


def _bits(local: bool) -> Query:
    def query(spark, sf):
        labels = cluster.wave_cluster(spark, builders.region_chain(spark, sf), k=2, steps=200, preset=ONE, connected=True, max_nodes=5_000 if local else 1)
        return rounded(labels.select("id", F.col("bits")[0].alias("b1"), F.col("bits")[1].alias("b2"), "cluster", "group_rep", "margin"), 5)

    return query


def relabel_region(spark, sf):
    nation = table(spark, sf, "nation").select(F.col("n_nationkey").cast("long").alias("id"), "n_regionkey")
    reps = nation.groupBy("n_regionkey").agg(F.min("id").alias("group_rep"))
    return cluster.relabel(nation.join(F.broadcast(reps), "n_regionkey").select("id", "group_rep")).select("id", "label")


def _modes(spark: SparkSession, sf: str, steps: int) -> tuple[DataFrame, DataFrame]:
    nodes, state = _history(spark, sf, steps)
    return nodes, spectrum.eigenvectors(spectrum.matched(wave.long_history(state), [1.0, 1.5], steps), nodes)


def eigenvectors_trade(spark, sf):
    """Matched sums scaled to unit degree norm, positive at the smallest id."""
    return rounded(_modes(spark, sf, 32)[1])


def gathered_trade(spark, sf):
    """Whole vectors as each node holds them after a gather, laid out by place."""
    whole = spectrum.gather_vectors(_modes(spark, sf, 32)[1])
    return rounded(whole.select("j", F.posexplode("vector").alias("place", "component")))


def vector_angle_trade(spark, sf):
    """Angle between the vectors read after 32 and after 48 steps."""
    nodes, a = _modes(spark, sf, 32)
    return rounded(metrics.vector_angle(a, _modes(spark, sf, 48)[1], nodes), 4)


def growth_cases_ring(spark, sf):
    """Which critical cases the eigenvalues of a ring hold, at a speed within the limit and at it; its nodes are the months in which there are orders."""
    scratch = Scratch(spark, "months")
    months = table(spark, sf, "orders").select(F.month("o_orderdate").alias("m")).where("m is not null").distinct()
    placed = scratch.save(ordered(months, ["m"], scratch))
    lams = placed.select((1 - F.cos(2 * np.pi * F.col("place") / placed.count())).alias("lam"))
    parts = [bounds.growth_cases(lams, c2).withColumn("c2", F.lit(c2)) for c2 in (1.99, 2.0)]
    return parts[0].unionByName(parts[1])


def state_costs(spark, sf):
    """Bytes a node keeps by kind of run, and numbers sent when nodes learn whole vectors."""
    kinds = [(r, f, h, metrics.state_bytes(r, f, h), metrics.gather_messages(1_000 * r, f)) for r in (1, 8) for f in (0, 1, 4) for h in (0, 200)]
    return spark.createDataFrame(kinds, "seeds int, frequencies int, history int, bytes long, gather long")


# --- eigenvalues ----------------------------------------------------------------------------------


def _path(spark: SparkSession, n: int) -> DataFrame:
    return builders.line(spark, n, 1, 1.0)


def eigenvalues_path(spark, sf):
    """Exact eigenvalues of an even path: the months in which there are orders, in a row."""
    months = table(spark, sf, "orders").select(F.month("o_orderdate").alias("m"))
    return rounded(baselines.eigenvalues_exact(builders.row(months)))


def orthogonal_path(spark, sf):
    """The three lowest eigenvalues but zero of an even path, by block iteration with small Gram matrices."""
    scratch = Scratch(spark, "block")
    edges = scratch.save(_path(spark, 8))
    _, values = baselines.orthogonal(spark, edges, wave.initial_state(nodes_of(edges), 4), 32, every=8, scratch=scratch)
    return rounded(spark.createDataFrame([(j + 1, float(v)) for j, v in enumerate(values[:3])], "j int, lam double"), 4)


def subspace_path(spark, sf):
    """The three lowest eigenvalues of a path of 8 from the subspace of a wave's history, to two digits."""
    edges = _path(spark, 8)

    def heard(part: pd.DataFrame) -> pd.DataFrame:
        g = cluster.LocalGraph.of(part["src"].to_numpy(), part["dst"].to_numpy(), part["w"].to_numpy())
        omega, _ = cluster.local_modes(g, 3, C2, 256, cluster.Preset(frequencies="subspace"))
        return pd.DataFrame({"j": np.arange(1, len(omega) + 1), "omega": omega})

    found = edges.groupBy(F.lit(0).alias("all")).applyInPandas(heard, "j int, omega double")
    return rounded(found.select("j", bounds.lambda_of("omega", C2).alias("lam")), 2)


# --- clusters -------------------------------------------------------------------------------------


def line_recursive(spark, sf):
    """A line of 32 with a very weak link in the middle and weak ones at the quarters, cut twice."""
    i = F.col("id")
    links = spark.range(1, 32).select(i.alias("src"), (i + 1).alias("dst"), F.when(i == 16, 0.01).when(i.isin(8, 24), 0.05).otherwise(1.0).alias("w"))
    return _reps(cluster.recursive_bisect(spark, symmetrize(links), 2))


def region_five(spark, sf):
    """Nations where all regions are tied alike, so that four frequencies are close: as many steps as it takes to part them."""
    return _reps(cluster.wave_cluster(spark, builders.region_trade(spark, sf), k=4, preset=cluster.Preset(parted=0.01), connected=True), "n_nationkey")


def five_clusters(spark, sf):
    """Rooms by the wave run of the upper floor, once, and the lower floor as it is."""
    return _five(builders.customer_rooms(spark, sf))


def pair_swap_line(spark, sf):
    """A bad split of a line of ten, mended by swaps of pairs."""
    edges = builders.line(spark, 10, 5, 0.1)
    bad = spark.range(1, 11).select("id", (F.col("id") % 2).cast("int").alias("bit"))
    out = baselines.pair_swap(edges, bad)
    head = out.where("id = 1").select(F.col("bit").alias("head"))
    return out.crossJoin(F.broadcast(head)).select("id", (F.col("bit") == F.col("head")).alias("with_first"))


# --- rounds to converge ---------------------------------------------------------------------------


def _rings(spark: SparkSession) -> DataFrame:
    """All rings as one edge table: node i of ring n is n * 1000 + i."""
    size = spark.createDataFrame([(n,) for n in RINGS], "n long").withColumn("i", F.explode(F.sequence(F.lit(0), F.col("n").cast("int") - 1)))
    a, b = F.col("n") * 1000 + F.col("i"), F.col("n") * 1000 + F.pmod(F.col("i") + 1, F.col("n"))
    ends = size.select("n", F.explode(F.array(F.struct(a.alias("src"), b.alias("dst")), F.struct(b.alias("src"), a.alias("dst")))).alias("e"))
    return ends.select("n", "e.src", "e.dst", F.lit(1.0).alias("w"))


def _heard(part: pd.DataFrame) -> pd.DataFrame:
    g = cluster.LocalGraph.of(part["src"].to_numpy(), part["dst"].to_numpy(), part["w"].to_numpy())
    rows = []
    for steps in SPANS:
        omega, _ = cluster.local_modes(g, 1, C2, steps, ONE)
        if len(omega):
            rows.append((part["n"].iloc[0], steps, float(omega[0])))
    return pd.DataFrame(rows, columns=["n", "steps", "omega"])


def _mixed(part: pd.DataFrame) -> pd.DataFrame:
    """Rounds until a lazy walk from the first node is within a quarter of even, in total variation."""
    g = cluster.LocalGraph.of(part["src"].to_numpy(), part["dst"].to_numpy(), part["w"].to_numpy())
    pi, even, rounds = np.zeros(len(g.ids)), g.deg / g.deg.sum(), 0
    pi[0] = 1.0
    while 0.5 * np.abs(pi - even).sum() > 0.25:
        pi = 0.5 * pi + 0.5 * np.bincount(g.dst, g.p * pi[g.src], len(g.ids))
        rounds += 1
    return pd.DataFrame({"n": [part["n"].iloc[0]], "walk_rounds": [rounds]})


def ring_convergence(spark, sf):
    """Measured on rings: steps until a wave's lowest peak is settled, and rounds until a lazy walk has mixed."""
    edges = _rings(spark)
    heard = edges.groupBy("n").applyInPandas(_heard, "n long, steps int, omega double")
    both = heard.join(heard.select("n", (F.col("steps") * 2).alias("steps"), F.col("omega").alias("last")), ["n", "steps"])
    near = F.abs(F.col("omega") - F.col("last")) <= F.greatest(0.02 * F.col("omega"), 2 * np.pi / F.col("steps"))
    settled = both.where(near & (F.col("omega") * F.col("steps") >= 2 * np.pi * ONE.eta)).groupBy("n").agg(F.min("steps").cast("long").alias("wave_rounds"))
    walks = edges.groupBy("n").applyInPandas(_mixed, "n long, walk_rounds long")
    return settled.join(walks, "n")


def ring_slopes(spark, sf):
    """How rounds grow with the ring: the powers of N for waves and for walks."""
    slope = lambda c: F.regr_slope(F.log(c), F.log("n")).alias(f"{c}_power")
    return rounded(ring_convergence(spark, sf).agg(slope("wave_rounds"), slope("walk_rounds")), 4)


def stable_steps_ring(spark, sf):
    """Steps from which the lowest frequency of a ring stays within two hundredths of its last value."""
    heard = _rings(spark).groupBy("n").applyInPandas(_heard, "n long, steps int, omega double")
    parts = [metrics.steps_to_stable(heard.where(F.col("n") == n)).select(F.lit(n).alias("n"), F.col("steps").cast("long").alias("steps")) for n in RINGS]
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).unionByName(parts[3])


# --- estimation and search ------------------------------------------------------------------------

ROUNDS = [1, 2, 5, 10, 20, 50, 100, 200, 500, 1000]


def _errors(spark: SparkSession, sf: str) -> DataFrame:
    edges, x = builders.building(spark), _readings(spark, sf)
    parts = [estimation.consensus_errors(x, edges, of(spark.range(128)), ROUNDS).withColumn("strategy", F.lit(name)) for name, of in (("two", estimation.floor_partition), ("five", _five))]
    return parts[0].unionByName(parts[1])


def consensus_errors(spark, sf):
    """Distance from the cluster means after so many rounds, for two clusters and for the five of the wave run."""
    return rounded(_errors(spark, sf).select("strategy", "rounds", "rms"), 4)


def rounds_to_accuracy(spark, sf):
    """Rounds in which two clusters come as near to their means as five do in ten."""
    found = Scratch(spark, "rounds").save(_errors(spark, sf))
    goal = found.where("strategy = 'five' and rounds = 10").first()["rms"]
    return estimation.iterations_to_tol(found.where("strategy = 'two'"), goal)


def contaminant_rk4_8(spark, sf):
    air = estimation.flows(builders.building(spark))
    return rounded(estimation.contaminant_run(spark, air, estimation.rooms(spark), 8, method="rk4").select("id", "c"), 9)


def _search(method: str, steps: int) -> Query:
    def query(spark, sf):
        scratch = Scratch(spark, "search")
        functions = scratch.save(search.prior(_belief(spark, sf), search.basis(spark, 3)))
        paths, _ = search.run(spark, scratch.save(_agents(spark, sf)), functions, steps, scratch=scratch, method=method)
        return rounded(paths.where(F.col("t") == steps).select("id", "x", "y"), 5)

    return query


def _search_statistics(method: str, steps: int) -> Query:
    def query(spark, sf):
        scratch = Scratch(spark, "search")
        functions = scratch.save(search.prior(_belief(spark, sf), search.basis(spark, 3)))
        _, stats = search.run(spark, scratch.save(_agents(spark, sf)), functions, steps, scratch=scratch, method=method)
        return rounded(stats.select("k1", "k2", "s"), 4)

    return query


def asof_reading(spark, sf):
    """Each order with the last event of its customer up to the order's time."""
    orders = table(spark, sf, "orders").select("o_orderkey", F.col("o_custkey").cast("long").alias("who"), F.col("o_orderdate").cast("timestamp").alias("at"))
    events = table(spark, sf, "events").select(F.col("user_id").cast("long").alias("who"), F.col("ts").cast("timestamp").alias("at"), "event_id")
    return joins.asof(orders, events, "who", "at", ["event_id"]).select("o_orderkey", "event_id")


QUERIES: dict[str, Query] = {
    f.__name__: f
    for f in (
        wave_given_start, ring_wave, day_ring_wave_blocks, fft_trade, windowed_dft_kinds, detrended_trade, peaks_region, local_peaks_region, choose_k_region, relabel_region, eigenvectors_trade,
        gathered_trade, vector_angle_trade, growth_cases_ring, state_costs, eigenvalues_path, orthogonal_path, subspace_path, line_recursive, region_five, five_clusters, pair_swap_line,
        ring_convergence, ring_slopes, stable_steps_ring, consensus_errors, rounds_to_accuracy, contaminant_rk4_8, asof_reading,
    )
}
QUERIES |= {
    "bits_region": _bits(True), "bits_region_distributed": _bits(False), "search_rk4_1": _search("rk4", 1), "search_midpoint_2": _search("midpoint", 2),
    "search_statistics_rk4_1": _search_statistics("rk4", 1), "search_statistics_2": _search_statistics("midpoint", 2),
}
