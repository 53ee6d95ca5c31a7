"""Findings of the second round."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from ripplegraph import experiment_oracles, experiments, queries
from ripplegraph.operators import cluster, estimation
from ripplegraph.oracles import ORACLES
from ripplegraph.queries import QUERIES
from ripplegraph.sources import builders, tables

QUERIES = QUERIES | experiments.QUERIES
ORACLES = ORACLES | experiment_oracles.ORACLES


def rows_of_sql(name, folder, *tables):
    """Rows of a query's SQL over the tables of a folder."""
    con = duckdb.connect()
    for t in tables:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{folder}/{t}.parquet'")
    got = con.sql(ORACLES[name])
    return got.columns, sorted(got.fetchall(), key=str)


def same_as_sql(spark, name, folder, *tables):
    names, want = rows_of_sql(name, folder, *tables)
    got = QUERIES[name](spark, str(folder))
    assert sorted(got.columns) == sorted(names)
    assert sorted((tuple(r) for r in got.select(*names).collect()), key=str) == want and want


def test_weeks_go_by_the_nearest_second_as_in_the_sql(spark, tmp_path):
    stamps = ["2024-01-03 23:59:58.9", "2024-01-03 23:59:59.4", "2024-01-03 23:59:59.5", "2024-01-03 23:59:59.7", "2024-01-04 00:00:00", "2024-01-10 23:59:59.499999"]
    con = duckdb.connect()
    values = ", ".join(f"({i}, TIMESTAMP '{t}', 7, '{'ab'[i % 2]}')" for i, t in enumerate(stamps))
    con.sql(f"COPY (SELECT * FROM (VALUES {values}) t(event_id, ts, user_id, event_type)) TO '{tmp_path}/events.parquet'")
    same_as_sql(spark, "weekly_event_flow", tmp_path, "events")


def test_close_modes_are_parted():
    """Three blocks of two tied so alike that their two lowest frequencies share a peak of a short run."""
    rows = [(2 * b, 2 * b + 1, 1.0) for b in range(3)] + [(0, 2, 0.02), (2, 4, 0.02), (0, 4, 0.0201)]
    a, b, w = (np.array(x) for x in zip(*rows, strict=True))
    g = cluster.LocalGraph.of(np.concatenate((a, b)), np.concatenate((b, a)), np.concatenate((w, w)))
    preset = cluster.Preset(parted=0.01)
    steps = cluster.parting_steps(g, 2, 1.99, preset)
    assert steps > cluster.stable_steps(g, 1.99, preset)
    omega, _ = cluster.local_modes(g, 2, 1.99, steps, preset)
    exact = np.arccos(1 - 1.99 * np.linalg.eigvalsh(g.dense())[1:3] / 2)
    assert np.allclose(omega, exact, atol=2 * np.pi / steps)


def test_regions_tied_alike_are_parted_at_any_size(spark):
    same_as_sql(spark, "region_five", "/root/testdata/sf0.1", "nation")


def test_every_label_counts_towards_quality(spark, monkeypatch):
    """More labels than 20,000 of a class; as bitmaps and joined by id, with awkward ids and qualities."""
    from ripplegraph.llm import op9_quality
    from ripplegraph.plans.scratch import Scratch

    many = spark.range(30_000).select(F.col("id").alias("doc_id"), F.lit(1).alias("quality"))
    odd = spark.createDataFrame([(-1, 1), (-32_769, 0), (1 << 40, 1), (5, 7), (None, 1), (40_000, None)], "doc_id long, quality int").union(spark.createDataFrame([(-32_769, 1)], "doc_id long, quality int"))
    docs = many.select("doc_id").union(odd.select("doc_id").distinct()).union(spark.createDataFrame([(99_999,)], "doc_id long")).withColumn("text", F.lit("a"))
    want = {i: 1 for i in range(30_000)} | {-1: 1, -32_769: 1, 1 << 40: 1, 5: None, 99_999: None, None: None, 40_000: None}
    for bound in (50_000, 0):
        monkeypatch.setattr(op9_quality, "BROADCAST_ROWS", bound)
        scratch = Scratch(spark, "t")
        rows = op9_quality.marked(docs, op9_quality.labelled(many.where("doc_id <> 5").union(odd), scratch), scratch).collect()
        assert {r.doc_id: r.quality for r in rows} == want and len(rows) == docs.count()
        assert 5_000 < sum(r.fitting for r in rows) < 7_000 and not any(r.fitting for r in rows if r.quality is None)


def test_searched_vectors_equal_brute_force(spark):
    """Blocks and spans, equal vectors (smaller ids win), and a common vector; nothing is compared outside the asked rows."""
    from ripplegraph.operators import neighbours

    x = np.random.default_rng(3).normal(size=(400, 8))
    x[50:90] = x[7]
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    ids = np.arange(400)
    cos = x @ x.T
    np.fill_diagonal(cos, -2)
    want = {(i, j) for i in range(0, 400, 20) for j in sorted(range(400), key=lambda j: (-round(cos[i, j], 12), j))[:5]}
    row, at, w = neighbours._searched(ids[::20], x[::20], ids, x, 5, rows=3, span=37)
    assert set(zip(ids[::20][row].tolist(), at.tolist())) == want and np.allclose(w, cos[ids[::20][row], at])
    vecs = spark.createDataFrame([(i, [float(v) for v in row]) for i, row in enumerate(x)], "id long, v array<double>")
    rows = neighbours.searched_nearest(vecs.where("id % 20 = 0"), vecs, 5, block=30, least_parts=3).collect()
    assert {(r.src, r.dst) for r in rows} == want and len(rows) == 100
    odd = spark.createDataFrame([(1, [1.0, 0.0]), (2, [1.0, 0.0]), (3, [2.0, 0.0]), (4, None), (5, [0.0, 0.0]), (6, [1.0, None]), (7, [float("nan"), 1.0]), (8, []), (9, [float("inf"), 1.0]), (None, [1.0, 1.0])], "id long, v array<float>")
    assert sorted((r.src, r.dst, r.w) for r in neighbours.searched_nearest(odd, odd, 1).collect()) == [(1, 2, 1.0), (2, 1, 1.0), (3, 1, 1.0)]
    assert neighbours.searched_nearest(vecs.limit(0), vecs, 5).count() == neighbours.searched_nearest(vecs, vecs.limit(0), 5).count() == 0


def test_documents_joined_by_words_equal_the_sql(spark, tmp_path):
    """Blocks of 5 documents, texts of more than 255 words in common, documents without links and without text."""
    from ripplegraph.sources import builders

    draw = np.random.default_rng(4)
    names = [f"w{i}" for i in range(30)]
    texts = [" ".join(draw.choice(names[:15] if i < 14 else names[15:], 6)) for i in range(28)] + [" ".join(f"x{i}" for i in range(300))] * 4 + [None, "", "alone in here"]
    docs = spark.createDataFrame([(100 - 3 * i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    docs.coalesce(1).toPandas().to_parquet(f"{tmp_path}/documents.parquet")
    names, want = rows_of_sql("doc_words_graph", tmp_path, "documents")
    got = builders.doc_words_joined(spark, str(tmp_path), block=5)
    assert sorted(got.columns) == sorted(names)
    assert sorted((tuple(r) for r in got.collect()), key=str) == want
    assert len({r[3] for r in want if r[1]}) >= 3 and max(r[2] for r in want) == 900


def test_documents_are_joined_whole(spark):
    same_as_sql(spark, "doc_words_graph", "/root/testdata/sf0.001", "documents")


def reads(query, spark, folder):
    """(names of the given tables that a query reads, its rows)."""
    seen = []
    real = tables.table

    def watched(session, sf_dir, name):
        seen.append(name)
        return real(session, sf_dir, name)

    with pytest.MonkeyPatch.context() as patch:
        for module in (builders, queries, experiments):
            patch.setattr(module, "table", watched)
        rows = QUERIES[query](spark, str(folder)).collect()
    return set(seen), rows


def test_building_graph_reads_a_given_table(spark, sf):
    assert reads("building_graph", spark, sf)[0] == {"customer"}
    same_as_sql(spark, "building_graph", sf, "customer")


def test_building_clusters_reads_a_given_table(spark, sf):
    assert reads("building_clusters", spark, sf)[0] == {"customer"}
    same_as_sql(spark, "building_clusters", sf, "customer")


def test_five_clusters_reads_a_given_table(spark, sf):
    assert reads("five_clusters", spark, sf)[0] == {"customer"}
    same_as_sql(spark, "five_clusters", sf, "customer")


def test_kalman_room49_reads_a_given_table(spark, sf):
    """The rooms are read; all 128 are there, so the numbers are those of the whole building."""
    seen, rows = reads("kalman_room49", spark, sf)
    assert seen == {"customer"} and len(rows) == 3
    edges = builders.building(spark)
    floors = estimation.experiment(edges, estimation.flows(edges), estimation.floor_partition(spark.range(128)), estimation.Filter(rounds=10))
    want = estimation.report(floors, queries.ROOM).first()
    assert next(r for r in rows if r.strategy == "floors_10").rmse == pytest.approx(want.rmse, abs=1e-6)


def test_basis_table_reads_a_given_table(spark, sf):
    assert reads("basis_table", spark, sf)[0] == {"lineitem"}
    same_as_sql(spark, "basis_table", sf, "lineitem")


def test_best_ratio_cut_line_reads_a_given_table(spark, sf):
    assert reads("best_ratio_cut_line", spark, sf)[0] == {"lineitem"}
    same_as_sql(spark, "best_ratio_cut_line", sf, "lineitem")


def test_eigenvalues_path_reads_a_given_table(spark, sf):
    assert reads("eigenvalues_path", spark, sf)[0] == {"orders"}
    same_as_sql(spark, "eigenvalues_path", sf, "orders")


def test_growth_cases_ring_reads_a_given_table(spark, sf):
    assert reads("growth_cases_ring", spark, sf)[0] == {"orders"}
    same_as_sql(spark, "growth_cases_ring", sf, "orders")


def test_horizon_rules_reads_a_given_table(spark, sf):
    assert reads("horizon_rules", spark, sf)[0] == {"lineitem"}
    same_as_sql(spark, "horizon_rules", sf, "lineitem")


def test_closed_sums_equal_a_run():
    """Fourier sums from the ends of a run against those of all its steps, on a line with weak links."""
    n = 30
    a, w = np.arange(n - 1), np.where(np.isin(np.arange(n - 1), (9, 21)), 0.001, 1.0)
    g = cluster.LocalGraph.of(np.concatenate((a, a + 1)), np.concatenate((a + 1, a)), np.concatenate((w, w)))
    run, closed = cluster.Preset(), cluster.Preset(closed=True)
    for steps in (512, 4_096):
        z = np.fft.rfft(g.evolve(g.start(run), steps, 1.99) * cluster.window_values("hann", steps), axis=2)
        power = (g.deg[:, None, None] * np.abs(z) ** 2).sum(axis=(0, 1))
        part = next(iter(cluster.closed_sums(g, g.start(run), steps, 1.99)))
        assert np.allclose((g.deg[:, None, None] * np.abs(part) ** 2).sum(axis=(0, 1)), power[:32], rtol=1e-5, atol=1e-9 * power.max())
        for (o, x), (p, y) in [(cluster.local_modes(g, 2, 1.99, steps, run), cluster.local_modes(g, 2, 1.99, steps, closed))]:
            assert np.allclose(o, p) and (cluster.codes(x)[0] == cluster.codes(y)[0]).all()
    assert cluster.stable_steps(g, 1.99, run) == cluster.stable_steps(g, 1.99, closed)
