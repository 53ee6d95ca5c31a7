"""Waves over near points, without rows of links."""

import math

from pyspark.sql import functions as F

from ripplegraph import queries
from ripplegraph.operators import cluster, near, search


def places(spark, n, groups=1):
    """Points in some strips too far apart to meet, and one point alone."""
    key = F.col("id")
    strip = F.pmod(key, F.lit(groups)).cast("double")
    own = spark.range(1, n).select((key * 3).alias("id"), (F.pmod(key * 7919, F.lit(1009)) / 1009.0 + strip * 2).alias("x"), (F.pmod(key * 104729, F.lit(1013)) / 1013.0).alias("y"))
    return own.unionByName(spark.createDataFrame([(1, 40.0, 40.0)], own.schema))


def same(one, other):
    a, b = ({r["id"]: r for r in x.collect()} for x in (one, other))
    assert a.keys() == b.keys() and len(a) > 0
    for i, r in a.items():
        assert (r["bits"], r["cluster"], r["group_rep"]) == (b[i]["bits"], b[i]["cluster"], b[i]["group_rep"]) and math.isclose(r["margin"], b[i]["margin"], rel_tol=1e-6, abs_tol=1e-9)


def test_blocks_in_a_batch_give_the_labels_of_the_links(spark, monkeypatch):
    points = places(spark, 500, 2)
    want = cluster.wave_cluster(spark, search.proximity(points, 0.25), k=2, steps=64)
    monkeypatch.setattr(near, "wave_cluster", None)
    monkeypatch.setattr(near, "PAIRS_OF_POINTS", 1)
    same(near.near_cluster(spark, points, 0.25, k=2, steps=64), want)


def test_blocks_in_tasks_give_the_labels_of_the_links(spark, monkeypatch):
    points = places(spark, 300, 2)
    want = cluster.wave_cluster(spark, search.proximity(points, 0.4), k=2, steps=12)
    monkeypatch.setattr(near, "wave_cluster", None)
    monkeypatch.setattr(near, "PAIRS_OF_POINTS", 1)
    monkeypatch.setattr(near.NearParts.__init__, "__defaults__", (10,))
    monkeypatch.setattr(near, "ROWS", 4)
    same(near.near_cluster(spark, points, 0.4, k=2, steps=12, held_bytes=0), want)


def test_sparse_points_and_ids_with_several_places_are_rows(spark):
    points = places(spark, 60).unionByName(places(spark, 20).select("id", "y", F.col("x").alias("x")))
    want = cluster.wave_cluster(spark, search.proximity(points, 0.1), steps=32)
    same(near.near_cluster(spark, points, 0.1, steps=32), want)


def test_the_search_writes_no_links(spark, sf, monkeypatch):
    """Links between all agents grow with their square."""
    monkeypatch.setattr(search, "proximity", None)
    monkeypatch.setattr(near, "proximity", None)
    row = queries.search_agreement(spark, places(spark, 800).where("id > 1"), queries._belief(spark, sf), steps=1).first()
    assert row["gap"] < 1e-6 and math.isclose(row["coverage"], row["of_clusters"], rel_tol=1e-6)
