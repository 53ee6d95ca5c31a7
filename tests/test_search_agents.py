"""The two modes of the search are compared over all agents."""

from pyspark.sql import functions as F

from ripplegraph import queries
from ripplegraph.operators import search


def test_every_supplier_searches(spark, sf, monkeypatch):
    """An agent beyond the first forty counts, and so does one that the clustered search loses."""
    some = lambda *_: spark.range(38, 46).select("id", (F.col("id") % 3 / 3.0).alias("x"), (F.col("id") % 5 / 5.0).alias("y"))
    seen = []

    def run(spark, agents, functions, steps, mode="central", **_):
        seen.append(agents.count())
        moved = agents.select(F.lit(1).alias("t"), "id", "x", (F.col("y") + F.when(F.col("id") == 45, F.lit(0.5 if mode == "clustered" else 0.0)).otherwise(0.0)).alias("y"))
        return moved, functions.withColumn("s", F.lit(1.0))

    monkeypatch.setattr(queries, "_agents", some)
    monkeypatch.setattr(search, "run", run)
    row = queries.search_modes_agree(spark, sf).first()
    assert seen == [8, 8] and row["gap"] == 0.5 and row["coverage"] == row["of_clusters"] > 0


def test_a_lost_agent_is_a_gap(spark):
    a = spark.createDataFrame([(0, 1, 0.0, 0.0), (0, 2, 0.0, 0.0)], "t int, id long, x double, y double")
    assert search.trajectory_gap(a, a.where("id = 1")).first()["gap"] == float("inf") and search.trajectory_gap(a, a).first()["gap"] == 0.0
