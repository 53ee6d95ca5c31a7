"""Queries without SQL against numpy, and pieces that no query shows."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from ripplegraph.functions import bounds
from ripplegraph.operators import baselines, cluster, estimation, graph, joins, wave
from ripplegraph.operators.estimator import WaveClusterer, as_arrays
from ripplegraph.plans.ordered import ordered
from ripplegraph.plans.scratch import Scratch
from ripplegraph.queries import QUERIES
from ripplegraph.sources import builders
from ripplegraph.streaming import evolving


def local(edges):
    rows = edges.toPandas()
    return cluster.LocalGraph.of(rows["src"].to_numpy(), rows["dst"].to_numpy(), rows["w"].to_numpy())


def exact_sides(g, ids=None):
    """Signs of the second eigenvector, and which of them are clear."""
    _, v = baselines.exact_pairs(g)
    clear = np.abs(v[:, 1]) > 1e-3 * np.abs(v[:, 1]).max()
    return (v[:, 1] > 0) == (v[0, 1] > 0), clear


def test_recursive_regions_equal_exact_recursion(spark, sf):
    g = local(builders.region_chain(spark, sf))
    got = {r.id: r.group_rep for r in QUERIES["region_recursive"](spark, sf).collect()}
    side, _ = exact_sides(g)
    expected = {}
    for part in (True, False):
        own = np.flatnonzero(side == part)
        keep = np.isin(g.src, own) & np.isin(g.dst, own)
        h = cluster.LocalGraph.of(g.ids[g.src[keep]], g.ids[g.dst[keep]], (g.p * g.deg[g.src])[keep])
        inner, _ = exact_sides(h)
        for bit in (True, False):
            members = h.ids[inner == bit]
            expected |= dict.fromkeys(members.tolist(), int(members.min()))
    assert got == expected


def chain_sides(labels, edges):
    """Share of clearly placed nodes on the side that the exact vector gives, by component."""
    got = {r.id: r.group_rep for r in labels.collect()}
    rows = edges.toPandas()
    parent = {x: x for x in rows["src"]}

    def root(x):
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for a, b in zip(rows["src"], rows["dst"], strict=True):
        parent[root(a)] = root(b)
    rows["c"] = rows["src"].map(root)
    shares = []
    for _, part in rows.groupby("c"):
        g = cluster.LocalGraph.of(part["src"].to_numpy(), part["dst"].to_numpy(), part["w"].to_numpy())
        side, clear = exact_sides(g)
        mine = np.array([got[i] for i in g.ids.tolist()]) == got[int(g.ids[0])]
        shares.append((mine == side)[clear].mean())
    assert set(got) == set(parent)
    return np.array(shares)


def test_conversations_are_cut_as_exactly(spark, sf):
    shares = chain_sides(QUERIES["conv_chain_clusters"](spark, sf), builders.conv_chain(spark, sf))
    assert (shares == 1).mean() > 0.95 and shares.mean() > 0.98


def test_user_lines_are_cut_as_exactly(spark, sf):
    shares = chain_sides(QUERIES["user_line_cut"](spark, sf), builders.user_line(spark, sf))
    assert np.median(shares) == 1 and shares.mean() > 0.9


def test_nearest_vectors_equal_brute_force(spark, sf):
    rows = spark.read.parquet(f"{sf}/embeddings.parquet").toPandas()
    x = np.stack(rows["embedding"].to_numpy()).astype(float)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    ids = rows["vec_id"].to_numpy()
    cos = x @ x.T
    cos[ids[:, None] == ids[None, :]] = -2
    links = {}
    for i in np.flatnonzero(ids % 20 == 0):
        for j in sorted(np.flatnonzero(cos[i] > -2), key=lambda j: (-cos[i, j], ids[j]))[:10]:
            a, b = int(ids[i]), int(ids[j])
            links[a, b] = links[b, a] = max(cos[i, j], 1e-9)
    deg = {}
    for (a, _), w in links.items():
        deg[a] = deg.get(a, 0) + w
    got = {r.id: r.deg for r in QUERIES["emb_knn_degrees"](spark, sf).collect()}
    assert got.keys() == deg.keys() and all(got[k] == pytest.approx(deg[k], abs=1e-4) for k in got)


def test_large_components_equal_batches(spark):
    """Distributed labels, with centred starts and without, against those of a batch."""
    for edges in (builders.line(spark, 20, 10, 0.1), builders.karate(spark)):
        for preset in (cluster.Preset(seeds=2), cluster.Preset(seeds=2, center=False)):
            near, far = (cluster.wave_cluster(spark, edges, steps=512, preset=preset, connected=True, max_nodes=m).orderBy("id").toPandas() for m in (5_000, 1))
            assert near["group_rep"].tolist() == far["group_rep"].tolist()
            assert np.allclose(near["margin"], far["margin"], rtol=1e-3, atol=1e-6)


def test_steps_by_joins_batches_and_blocks_agree(spark):
    edges = builders.line(spark, 60, 30)
    start = wave.initial_state(graph.nodes_of(edges), 2)
    a, b = (wave.run(spark, edges, start, 11, filters=[0.3], batch=x).orderBy("id").toPandas() for x in (True, False))
    assert np.allclose(a[["u0", "u1", "v0", "re0_1", "im0_0", "total1"]], b[["u0", "u1", "v0", "re0_1", "im0_0", "total1"]])
    c = wave.run_blocks(spark, edges, start, 11, q=3, block_rows=30).orderBy("id").toPandas()
    assert np.allclose(a[["u0", "u1", "v0"]], c[["u0", "u1", "v0"]])


def test_probes_by_joins_and_batches_agree(spark, monkeypatch):
    edges = builders.line(spark, 12, 6)
    start = wave.initial_state(graph.nodes_of(edges), 2)
    a = wave.probe_series(spark, edges, start, 10, 5).orderBy("id", "t").toPandas()
    monkeypatch.setattr(wave, "BROADCAST_ROWS", 0)
    b = wave.probe_series(spark, edges, start, 10, 5).orderBy("id", "t").toPandas()
    assert len(a) == 50 and np.allclose(a, b)


def test_steps_over_buckets_never_shuffle_edges(spark, monkeypatch):
    monkeypatch.setattr(wave, "BROADCAST_ROWS", 0)
    edges = builders.line(spark, 40, 20)
    scratch = Scratch(spark, "t")
    rows, few = wave.laid_out(wave.with_own_rows(graph.walk_weights(edges)), scratch)
    assert not few
    state = scratch.save(wave.initial_state(graph.nodes_of(edges)))
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        two = wave.step(rows, wave.step(rows, state, 0.01, 1.0, 1.99), 0.01, 1.0, 1.99)
        plan = two._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert plan.count("Exchange hashpartitioning(") <= 3 and plan.count("Bucketed: true") == 2  # the first state, and the messages of each step


def test_places_and_running_sums(spark):
    rows = spark.range(1000).select("id", ((F.col("id") * 37) % 1000).alias("k"), F.lit(0.5).alias("x"))
    got = ordered(rows, ["k"], Scratch(spark, "t"), {"sum": F.col("x")}).orderBy("place").toPandas()
    assert got["k"].tolist() == list(range(1000)) and got["place"].tolist() == list(range(1000)) and np.allclose(got["sum"], 0.5 * np.arange(1, 1001))
    assert ordered(rows.limit(0), ["k"], Scratch(spark, "t")).count() == 0


def test_asof(spark):
    left = spark.createDataFrame([(1, 5, "a"), (1, 1, "b"), (2, 9, "c"), (None, 9, "d"), (1, None, "e")], "k long, t long, x string")
    right = spark.createDataFrame([(1, 2, 7), (1, 5, 8), (1, 5, 9), (1, 6, 1), (None, 1, 3), (2, None, 4)], "k long, t long, v long")
    assert {r.x: r.v for r in joins.asof(left, right, "k", "t", ["v"]).collect()} == {"a": 9, "b": None, "c": None, "d": None, "e": None}


def test_estimator_and_vectors(spark):
    model = WaveClusterer(k=1, steps=512).fit(builders.line(spark, 20, 10))
    out = {r.id: r.group_rep for r in model.transform(spark.range(0, 22)).collect()}
    assert out == {0: None, 21: None, **{i: 1 if i <= 10 else 11 for i in range(1, 21)}}
    arrays = as_arrays(model.transform(spark.range(1, 3)), "features")
    assert dict(arrays.dtypes)["features"] == "array<double>" and as_arrays(arrays, "features").count() == 2


def test_growth_cases(spark):
    lams = spark.createDataFrame([(0.0,), (0.5,), (0.5,), (2.0,)], "lam double")
    assert tuple(bounds.growth_cases(lams, 1.99).first()) == (True, True, False)
    assert tuple(bounds.growth_cases(lams.where("lam = 2"), 2.0).first()) == (False, False, True)


def test_labels_are_made_anew_only_on_drift(spark):
    old, small, large = builders.line(spark, 10, 5), builders.line(spark, 10, 5, 0.11), builders.line(spark, 10, 2, 0.1)
    labels = spark.createDataFrame([(0,)], "x int")
    again = lambda e: spark.createDataFrame([(1,)], "x int")
    assert estimation.maybe_recluster(old, small, labels, again).first().x == 0
    assert estimation.maybe_recluster(old, large, labels, again).first().x == 1


def test_evolving_cluster(spark, tmp_path):
    import shutil

    def batch(name, weak_at):
        builders.line(spark, 8, weak_at, 0.01).coalesce(1).write.parquet(f"{tmp_path}/{name}")
        (part,) = [p for p in (tmp_path / name).iterdir() if p.suffix == ".parquet"]
        (tmp_path / "in").mkdir(exist_ok=True)
        shutil.copy(part, tmp_path / "in" / f"{name}.parquet")

    def go():
        stream = spark.readStream.schema("src long, dst long, w double").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
        cut = lambda e: cluster.wave_bisect(spark, e, steps=512, connected=True)
        evolving.evolving_cluster(stream, f"{tmp_path}/c", f"{tmp_path}/out", cut).awaitTermination(120)

    batch("a", 4)
    go()
    first = {r.id: r.group_rep for r in spark.read.parquet(f"{tmp_path}/out/labels/0").collect()}
    assert first == {i: 1 if i <= 4 else 5 for i in range(1, 9)}
    batch("b", 4)
    go()
    assert spark.read.parquet(f"{tmp_path}/out/graph/1").where("src = 1").first().w == 2
    assert {r.id: r.group_rep for r in spark.read.parquet(f"{tmp_path}/out/labels/1").collect()} == first


def test_stream_of_repeated_events_and_orders(spark, tmp_path):
    rows = [(1, "2024-01-01 00:00:00", 7), (1, "2024-01-01 00:00:00", 7), (2, "2024-01-01 10:00:00", 7), (3, "2024-01-05 00:00:00", 7), (4, "2024-01-09 00:00:00", None)]
    events = spark.createDataFrame(rows, "event_id long, ts string, user_id long").withColumn("ts", F.to_timestamp("ts"))
    events.coalesce(1).write.parquet(f"{tmp_path}/e")
    spark.createDataFrame([(70, 7, "2023-12-31 20:00:00"), (71, 8, "2024-01-01 00:00:00")], "o_orderkey long, o_custkey long, o_orderdate string").withColumn("o_orderdate", F.to_timestamp("o_orderdate")).coalesce(1).write.parquet(f"{tmp_path}/o")

    def shown(df, name):
        df.writeStream.format("memory").queryName(name).outputMode("append").option("checkpointLocation", f"{tmp_path}/{name}").trigger(availableNow=True).start().awaitTermination(120)
        return spark.table(name).collect()

    e = spark.readStream.schema(events.schema).parquet(f"{tmp_path}/e")
    assert sorted(r.event_id for r in shown(evolving.deduplicated(e), "once")) == [1, 2, 3, 4]
    o = spark.readStream.schema("o_orderkey long, o_custkey long, o_orderdate timestamp").parquet(f"{tmp_path}/o")
    assert sorted((r.o_orderkey, r.event_id) for r in shown(evolving.with_orders(o, e), "met")) == [(70, 1), (70, 1), (70, 2)]
