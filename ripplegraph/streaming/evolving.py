"""Graphs whose weights change: windowed weights from a stream of events, and clustering anew when they drift."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.query import StreamingQuery

from ripplegraph.operators.estimation import drift

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def transitions(events: DataFrame, late: str = "2 days") -> DataFrame:
    """(ts, user_id, last, event_type): each event with its user's one before, across micro-batches.

    The state of a user is its last event; it goes once the watermark has passed it. Inside a batch events
    are put in order; an event older than the state starts a pair of its own.
    """

    def follow(key: tuple, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        rows = pd.concat(parts).sort_values(["ts", "event_id"])
        last_ts, last = state.get if state.exists else (None, None)
        out = []
        for ts, kind in zip(rows["ts"], rows["event_type"], strict=True):
            micros = int(ts.value // 1000)
            if last is not None and micros >= last_ts:
                out.append((ts, key[0], last, kind))
            if last is None or micros >= last_ts:
                last_ts, last = micros, kind
        state.update((last_ts, last))
        state.setTimeoutTimestamp(max(last_ts // 1000 + 1, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame(out, columns=["ts", "user_id", "last", "event_type"])

    own = events.withWatermark("ts", late).select("ts", "user_id", "event_id", "event_type").where("user_id is not null")
    return own.groupBy("user_id").applyInPandasWithState(follow, "ts timestamp, user_id long, last string, event_type string", "ts long, event_type string", "append", "EventTimeTimeout")


def windowed_weights(pairs: DataFrame, length: str = "7 days", slide: str | None = None) -> DataFrame:
    """(start, a, b, w) of tumbling or sliding windows over ``(ts, last, event_type)``."""
    span = F.window("ts", length, slide) if slide else F.window("ts", length)
    return pairs.groupBy(span.alias("window"), F.col("last").alias("a"), F.col("event_type").alias("b")).agg(F.count("*").alias("w")).select(F.col("window.start").alias("start"), "a", "b", "w")


def sessions(events: DataFrame, gap: str = "2 days", late: str = "2 days") -> DataFrame:
    """(user_id, start, end, n): runs of a user's events without a gap; the streaming twin of the user line."""
    events = events.where("user_id is not null")
    own = events.withWatermark("ts", late) if events.isStreaming else events
    return own.groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count("*").alias("n")).select("user_id", F.col("s.start").alias("start"), F.col("s.end").alias("end"), "n")


def deduplicated(events: DataFrame, late: str = "2 days") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def with_orders(orders: DataFrame, events: DataFrame, within: str = "1 day", late: str = "2 days") -> DataFrame:
    """Events of a customer up to ``within`` after an order; both sides have watermarks, so state is bounded."""
    o = orders.withWatermark("o_orderdate", late)
    e = events.withWatermark("ts", late)
    near = (F.col("ts") >= F.col("o_orderdate")) & (F.col("ts") <= F.col("o_orderdate") + F.expr(f"interval {within}"))
    return o.join(e, (F.col("o_custkey") == F.col("user_id")) & near)


def evolving_cluster(weights: DataFrame, checkpoint: str, target: str, cluster: Callable[[DataFrame], DataFrame], limit: float = 0.1) -> StreamingQuery:
    """Each micro-batch of ``(src, dst, w)`` totals is merged into the graph; labels are made anew past the drift limit.

    Results are written by batch id, so a batch that is run again overwrites itself.
    """

    def merge(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        graph, labels = f"{target}/graph", f"{target}/labels"
        old = spark.read.parquet(f"{graph}/{number - 1}") if number else batch.limit(0)
        new = old.unionByName(batch).groupBy("src", "dst").agg(F.sum("w").alias("w"))
        new.write.mode("overwrite").parquet(f"{graph}/{number}")
        new = spark.read.parquet(f"{graph}/{number}")
        moved = 1.0 if not number else drift(old, new).first()["drift"]
        fresh = cluster(new) if moved is not None and moved > limit else spark.read.parquet(f"{labels}/{number - 1}") if number else cluster(new)
        fresh.write.mode("overwrite").parquet(f"{labels}/{number}")

    return weights.writeStream.foreachBatch(merge).option("checkpointLocation", checkpoint).outputMode("update").trigger(availableNow=True).start()
