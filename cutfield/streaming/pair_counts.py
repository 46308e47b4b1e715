"""Streaming surface over events: windowed counts, interval joins, refreshes, and per-user state."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle


def events_stream(spark: SparkSession, folder: str, schema: T.StructType) -> DataFrame:
    """Parquet files of events as a stream."""
    return spark.readStream.schema(schema).parquet(folder)


def deduplicated(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Each event once, within the watermark."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def tumbling(events: DataFrame, length: str = "1 hour", delay: str | None = None) -> DataFrame:
    """win_start, win_end, event_type, n in adjacent windows; rows later than the watermark are dropped."""
    rows = events.withWatermark("ts", delay) if delay else events
    return _named(rows.groupBy(F.window("ts", length).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")), "event_type")


def sliding(events: DataFrame, length: str = "2 hours", slide: str = "1 hour", delay: str | None = None) -> DataFrame:
    rows = events.withWatermark("ts", delay) if delay else events
    return _named(rows.groupBy(F.window("ts", length, slide).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")), "event_type")


def sessions(events: DataFrame, gap: str = "30 minutes", delay: str | None = None) -> DataFrame:
    """win_start, win_end, user_id, n of each user's visits; a visit ends ``gap`` after its last event."""
    rows = events.withWatermark("ts", delay) if delay else events
    return _named(rows.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")), "user_id")


def _named(df: DataFrame, key: str) -> DataFrame:
    return df.select(F.col("w.start").alias("win_start"), F.col("w.end").alias("win_end"), key, "n")


def view_then_purchase(events: DataFrame, within: str = "1 hour", delay: str | None = None) -> DataFrame:
    """user_id, view_id, purchase_id: purchases of a user within the span after a view; also stream to stream."""
    v = events.where("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("event_id").alias("view_id"), F.col("ts").alias("t1"))
    p = events.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase_id"), F.col("ts").alias("t2"))
    if delay:
        v, p = v.withWatermark("t1", delay), p.withWatermark("t2", delay)
    return v.join(p, F.expr(f"u = user_id and t2 >= t1 and t2 <= t1 + interval {within}")).select("user_id", "view_id", "purchase_id")


def with_static(events: DataFrame, dimension: DataFrame, on: str) -> DataFrame:
    """Stream to static join."""
    return events.join(dimension, on, "left")


def refresh(stream: DataFrame, step: Callable[[DataFrame, int], None], checkpoint: str):
    """A query that hands every batch of the stream to ``step``, such as one that updates couplings and starts inference from the last means."""
    return stream.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


class PresenceState(StatefulProcessor):
    """Per user: how often each event type was seen, kept across batches."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.counts = handle.getMapState("counts", "event_type string", "n long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        for pdf in rows:
            for kind, n in pdf["event_type"].value_counts().items():
                before = self.counts.getValue((kind,))[0] if self.counts.containsKey((kind,)) else 0
                self.counts.updateValue((kind,), (int(before + n),))
        found = [(key[0], k[0], v[0]) for k, v in self.counts.iterator()]
        yield pd.DataFrame(found, columns=["user_id", "event_type", "n"])

    def close(self) -> None:
        pass


def presence(events: DataFrame) -> DataFrame:
    """user_id, event_type, n after each batch, by a stateful processor (needs the RocksDB state store)."""
    return events.groupBy("user_id").transformWithStateInPandas(PresenceState(), "user_id long, event_type string, n long", "Update", "None")
