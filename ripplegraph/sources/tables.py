"""Reading tables and edge lists; schemas are given, never inferred from data."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EDGE_SCHEMA = "src long, dst long, w double"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def edges(spark: SparkSession, path: str, fmt: str = "parquet", schema: str = EDGE_SCHEMA, **options: str) -> DataFrame:
    """An edge list in Parquet, ORC, JSON lines, CSV or TSV, or ``text``: node, then neighbours, blank separated."""
    reader = spark.read.options(**options)
    if fmt == "text":
        parts = F.split("value", r"\s+")
        return reader.text(path).select(F.get(parts, F.lit(0)).try_cast("long").alias("src"), F.explode(F.slice(parts, 2, F.size(parts))).alias("dst")).select("src", F.col("dst").try_cast("long").alias("dst"), F.lit(1.0).alias("w")).where("src is not null and dst is not null")
    if fmt == "tsv":
        return reader.schema(schema).csv(path, sep="\t")
    return reader.schema(schema).format(fmt).load(path)


def from_sql(spark: SparkSession, query: str) -> DataFrame:
    return spark.sql(query)
