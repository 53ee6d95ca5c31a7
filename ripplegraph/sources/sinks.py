"""Writing graphs and results."""

from __future__ import annotations

from pyspark.sql import DataFrame


def edges(df: DataFrame, table: str, buckets: int) -> None:
    """A table bucketed by the sender of messages and sorted by the receiver: loops over it need no edge shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, "dst").sortBy("src").saveAsTable(table)


def write(df: DataFrame, path: str, mode: str = "overwrite", partition_by: list[str] | None = None) -> None:
    (df.write.mode(mode).partitionBy(*partition_by) if partition_by else df.write.mode(mode)).parquet(path)
