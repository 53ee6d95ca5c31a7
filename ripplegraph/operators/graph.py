"""Weighted undirected graphs as edge tables: ``edges(src, dst, w)`` with both directions stored."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def validate_graph(edges: DataFrame) -> DataFrame:
    """Typed edges without null ids, null, NaN or zero weights; a negative weight raises when the plan runs."""
    typed = edges.select(F.col("src").cast("long"), F.col("dst").cast("long"), F.col("w").cast("double"))
    known = typed.where("src is not null and dst is not null and w is not null and not isnan(w) and w <> 0")
    checked = F.when(F.col("w") > 0, F.col("w")).otherwise(F.raise_error(F.lit("negative edge weight")).cast("double"))
    return known.withColumn("w", checked)


def symmetrize(edges: DataFrame, how: str = "sum", keep_loops: bool = False) -> DataFrame:
    """Both directions of every link, parallel rows combined; one shuffle of the edges."""
    known = validate_graph(edges)
    both = known.unionByName(known.where("src <> dst").select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))
    if not keep_loops:
        both = both.where("src <> dst")
    return both.groupBy("src", "dst").agg({"sum": F.sum, "max": F.max, "mean": F.avg}[how]("w").alias("w"))


def degrees(edges: DataFrame) -> DataFrame:
    return edges.groupBy(F.col("src").alias("id")).agg(F.sum("w").alias("deg"))


def walk_weights(edges: DataFrame, form: str = "walk") -> DataFrame:
    """(src, dst, p, deg) with p = w / deg; ``sym`` divides by both square roots, ``lazy`` halves and loops."""
    own = edges.join(degrees(edges), edges["src"] == F.col("id")).drop("id")
    if form == "walk":
        return own.select("src", "dst", (F.col("w") / F.col("deg")).alias("p"), "deg")
    if form == "lazy":
        half = own.select("src", "dst", (F.col("w") / F.col("deg") / 2).alias("p"), "deg")
        return half.unionByName(degrees(edges).select(F.col("id").alias("src"), F.col("id").alias("dst"), F.lit(0.5).alias("p"), "deg"))
    other = degrees(edges).toDF("other", "other_deg")
    return own.join(other, own["dst"] == F.col("other")).select("src", "dst", (F.col("w") / F.sqrt(F.col("deg") * F.col("other_deg"))).alias("p"), "deg")


def nodes_of(edges: DataFrame) -> DataFrame:
    """(id, deg); a node of a valid edge table has a degree."""
    return degrees(edges)


def induced(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    keep = nodes.select("id")
    return edges.join(keep.toDF("src"), "src", "left_semi").join(keep.toDF("dst"), "dst", "left_semi").select(*edges.columns)


def threshold(edges: DataFrame, w_min: float) -> DataFrame:
    return edges.where(F.col("w") >= w_min)


def date_slice(events: DataFrame, column: str, low: str, high: str) -> DataFrame:
    """Rows from ``low`` up to, without, ``high``; the predicate reaches the scan."""
    return events.where((F.col(column) >= F.lit(low).cast("timestamp")) & (F.col(column) < F.lit(high).cast("timestamp")))


def sparsify(edges: DataFrame, share: float, seed: int = 1) -> DataFrame:
    """Keep links with probability min(1, share * w * (1/deg + 1/deg')), reweighted; both directions fall together."""
    deg = degrees(edges)
    a, b = deg.toDF("src", "da"), deg.toDF("dst", "db")
    odds = F.least(F.lit(1.0), F.lit(share) * F.col("w") * (1 / F.col("da") + 1 / F.col("db")))
    draw = F.pmod(F.xxhash64(F.least("src", "dst"), F.greatest("src", "dst"), F.lit(seed)), F.lit(1 << 30)) / float(1 << 30)
    return edges.join(a, "src").join(b, "dst").withColumn("odds", odds).where(draw < F.col("odds")).select("src", "dst", (F.col("w") / F.col("odds")).alias("w"))


def empty_edges(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([], "src long, dst long, w double")
