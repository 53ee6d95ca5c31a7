"""Plans and operators on small frames."""

from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

from ripplegraph import experiment_oracles, experiments
from ripplegraph.functions import sqlfuncs
from ripplegraph.operators import cluster, estimation, graph, metrics, spectrum, wave
from ripplegraph.operators.components import components
from ripplegraph.queries import QUERIES
from ripplegraph.oracles import ORACLES
from ripplegraph.sources import builders, sinks, tables
from ripplegraph.streaming import evolving


def frame(spark, rows):
    return spark.createDataFrame(rows, "src long, dst long, w double")


def test_symmetrize_cleans(spark):
    raw = frame(spark, [(1, 2, 1.0), (2, 1, 2.0), (1, 1, 5.0), (1, 3, 0.0), (None, 3, 1.0), (2, 3, None), (2, 3, float("nan")), (2, 3, 1.5), (2, 3, 0.5)])
    got = {(r.src, r.dst): r.w for r in graph.symmetrize(raw).collect()}
    assert got == {(1, 2): 3.0, (2, 1): 3.0, (2, 3): 2.0, (3, 2): 2.0}


def test_negative_weight_raises(spark):
    with pytest.raises(Exception, match="negative"):
        graph.symmetrize(frame(spark, [(1, 2, -1.0)])).collect()


def test_components(spark):
    rows = [(a, a + 1, 1.0) for a in range(0, 40)] + [(100, 101, 1.0), (103, 101, 1.0), (200, 200, 1.0)]
    got = {r.id: r.component for r in components(spark, frame(spark, rows).select("src", "dst")).collect()}
    assert got == {**dict.fromkeys(range(41), 0), 100: 100, 101: 100, 103: 100, 200: 200}


def test_components_of_nothing(spark):
    assert components(spark, graph.empty_edges(spark).select("src", "dst")).count() == 0


@pytest.mark.parametrize("bound", [50_000, 0])
def test_components_of_random_graphs(spark, monkeypatch, bound):
    """Minima broadcast, and beyond the bound written and joined."""
    monkeypatch.setattr("ripplegraph.operators.components.BROADCAST_ROWS", bound)
    pairs = np.random.default_rng(5).integers(0, 300, (220, 2)).tolist()
    least = {x: x for pair in pairs for x in pair}
    for _ in least:
        for a, b in pairs:
            least[a] = least[b] = min(least[a], least[b])
    got = {r.id: r.component for r in components(spark, spark.createDataFrame(pairs, "src long, dst long")).collect()}
    assert got == least


def test_step_needs_one_exchange_for_messages(spark):
    edges = builders.ring(spark, 8)
    rows = wave.with_own_rows(graph.walk_weights(edges))
    state = wave.initial_state(graph.nodes_of(edges))
    joins = lambda df: df._jdf.queryExecution().optimizedPlan().toString().count("Join Inner")
    assert joins(wave.step(rows, state, 0.01, 1.0, 1.99)) == joins(rows) + joins(state) + 1


def test_unrolling_does_not_change_results(spark):
    edges = builders.ring(spark, 7)
    start = wave.initial_state(graph.nodes_of(edges))
    a, b = (wave.run(spark, edges, start, 5, unroll=q).orderBy("id").toPandas()["u0"] for q in (1, 4))
    assert np.allclose(a, b, atol=1e-12)


def test_online_sums_equal_history(spark):
    edges = builders.ring(spark, 6)
    start = wave.initial_state(graph.nodes_of(edges))
    omega = 2 * np.pi * 3 / 16
    kept = wave.run(spark, edges, start, 16, filters=[omega]).orderBy("id").toPandas()
    full = wave.run(spark, edges, start, 16, history=True)
    sums = spectrum.dft(wave.long_history(full), [3], 16, "hann").orderBy("id").toPandas()
    assert np.allclose(kept["re0_0"], sums["re"]) and np.allclose(kept["im0_0"], sums["im"])
    fft = spectrum.fft(full, "hann", detrend=False).where("bin = 3").orderBy("id").toPandas()
    assert np.allclose(fft["re"], sums["re"]) and np.allclose(fft["im"], sums["im"])


def test_discrete_wave_equation(spark):
    edges = builders.ring(spark, 5)
    state = wave.run(spark, edges, wave.initial_state(graph.nodes_of(edges)), 6, history=True).orderBy("id").toPandas()
    u = np.array(state["series0"].tolist())
    lap = np.eye(5) - 0.5 * (np.roll(np.eye(5), 1, 0) + np.roll(np.eye(5), -1, 0))
    assert np.allclose(u[:, 2:] - 2 * u[:, 1:-1] + u[:, :-2], -1.99 * lap @ u[:, 1:-1])


def test_components_are_clustered_one_by_one(spark):
    two = builders.line(spark, 20, 10).unionByName(builders.line(spark, 20, 10).select(F.col("src") + 100, F.col("dst") + 100, "w").toDF("src", "dst", "w"))
    got = {r.id: r.group_rep for r in cluster.wave_bisect(spark, two, steps=512).collect()}
    assert got == {i + s: (1 if i <= 10 else 11) + s for i in range(1, 21) for s in (0, 100)}


def test_relabelled_ids_and_scaled_weights_give_the_same_partition(spark):
    edges = builders.line(spark, 20, 10)
    moved = edges.select((F.col("src") * 7 + 3).alias("src"), (F.col("dst") * 7 + 3).alias("dst"), (F.col("w") * 9).alias("w"))
    a = {r.id * 7 + 3: r.group_rep * 7 + 3 for r in cluster.wave_bisect(spark, edges, steps=512).collect()}
    assert a == {r.id: r.group_rep for r in cluster.wave_bisect(spark, moved, steps=512).collect()}


def test_gather_is_guarded(spark):
    v = spark.createDataFrame([(i, 1, 0.5) for i in range(5)], "id long, j int, component double")
    assert spectrum.gather_vectors(v).first()["vector"] == [0.5] * 5
    with pytest.raises(ValueError):
        spectrum.gather_vectors(v, limit=3)


def test_peaks_and_gap(spark):
    power = [float(x) for x in (0, 1, 30, 2, 1, 1, 20, 500, 900, 1000, 900, 100, 1)]
    found = spectrum.peaks(spark.createDataFrame(list(enumerate(power)), "bin int, power double"), 2, 24)
    assert [r.bin for r in found.orderBy("j").collect()] == [2, 9]
    assert spectrum.choose_k(found).first()["k"] == 1


def test_measures(spark):
    pred = spark.createDataFrame([(i, i // 4) for i in range(8)], "id long, cluster long")
    truth = pred.withColumnRenamed("cluster", "truth")
    assert metrics.rand_index(pred, truth).first()["ari"] == pytest.approx(1)
    assert metrics.nmi(pred, truth).first()["nmi"] == pytest.approx(1)
    assert metrics.recovery(pred, truth).first()["errors"] == 0
    stable = metrics.steps_to_stable(spark.createDataFrame([(8, 0.9), (16, 0.5), (32, 0.501), (64, 0.5)], "steps int, omega double"))
    assert stable.first()["steps"] == 16


def test_five_clusters_beat_two_at_ten_rounds(spark):
    rows = {r.strategy: r for r in QUERIES["kalman_room49"](spark, "/root/testdata/sf0.001").collect()}
    assert rows["five_10"].rms_cluster < rows["floors_10"].rms_cluster
    assert rows["floors_500"].rms_cluster < rows["floors_10"].rms_cluster


def test_consensus_keeps_the_mean(spark):
    edges = builders.ring(spark, 6)
    x = spark.range(6).select("id", F.col("id").cast("double").alias("x"))
    got = estimation.consensus(spark, x, edges, 40).toPandas()["x"]
    assert np.allclose(got, 2.5, atol=1e-3)


def test_sql_surface(spark):
    sqlfuncs.register(spark)
    assert spark.sql("SELECT wave_lambda(wave_omega(0.3D, 1.99D), 1.99D) AS x").first()["x"] == pytest.approx(0.3)
    assert spark.sql("SELECT count(*) AS n FROM ring_edges(5)").first()["n"] == 10
    assert spark.sql("SELECT count(*) AS n FROM spectrum_rows(array(1D, 2D, 1D, 0D))").first()["n"] == 3
    a = spark.range(1, 50).select("id", wave.start_value("id", 2).alias("a")).selectExpr("max(abs(a - wave_u0(id, 2L))) AS d").first()["d"]
    assert a == 0


def test_edge_formats(spark, tmp_path):
    edges = builders.ring(spark, 4)
    for fmt in ("parquet", "orc", "json", "csv"):
        edges.write.format(fmt).save(f"{tmp_path}/{fmt}")
        assert tables.edges(spark, f"{tmp_path}/{fmt}", fmt).count() == 8
    spark.createDataFrame([("1 2 3",), ("2 3",)], "value string").write.text(f"{tmp_path}/text")
    assert tables.edges(spark, f"{tmp_path}/text", "text").count() == 3
    sinks.write(edges, f"{tmp_path}/out")
    assert spark.read.parquet(f"{tmp_path}/out").count() == 8


def test_stream_equals_batch(spark, tmp_path):
    events = spark.read.parquet("/root/testdata/sf0.001/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    events.select("event_id", "ts", "user_id", "event_type", "value", "props").coalesce(1).write.parquet(f"{tmp_path}/in")
    stream = evolving.event_stream(spark, f"{tmp_path}/in")
    q = evolving.transitions(stream).writeStream.format("memory").queryName("pairs").outputMode("append").option("checkpointLocation", f"{tmp_path}/c").trigger(availableNow=True).start()
    q.awaitTermination(120)
    got = {(r.last, r.event_type): r["count"] for r in spark.table("pairs").groupBy("last", "event_type").count().collect()}
    assert got == {(r.a, r.b): r.w for r in builders.event_flow(spark, "/root/testdata/sf0.001").collect()}


def test_every_query_has_a_check_or_a_test():
    """Queries without SQL are named in a test that holds their results against numpy."""
    brute = {"emb_knn_degrees", "karate_cut", "region_recursive", "conv_chain_clusters", "user_line_cut", "doc_words_lang", "kalman_room49"}
    have = ORACLES | experiment_oracles.ORACLES
    every = QUERIES | experiments.QUERIES
    assert set(every) - set(have) == brute and set(have) <= set(every)
    here = "".join(p.read_text() for p in Path(__file__).parent.glob("test_*.py"))
    assert all(here.count(f'QUERIES["{name}"]') for name in brute)


def test_karate_equals_exact(spark, sf):
    assert all(r.group_rep == r.exact_rep for r in QUERIES["karate_cut"](spark, sf).collect())


def test_flagship(spark, sf):
    got = {r.n_nationkey: r.group_rep for r in QUERIES["cluster_region"](spark, sf).collect()}
    nation = spark.read.parquet(f"{sf}/nation.parquet").toPandas()
    first = nation.groupby("n_regionkey")["n_nationkey"].transform("min")
    assert got == dict(zip(nation["n_nationkey"], first, strict=True))


def test_doc_words_follow_the_language(spark, sf):
    assert QUERIES["doc_words_lang"](spark, sf).first()["purity"] > 0.9
