"""Continuous updates.

``stream_updates`` applies each micro-batch as one index version; the stream's ledger entry in the manifest
makes a batch that is replayed after a failure a no-op. Maintenance runs every ``every`` batches.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ivfspark.operators.updates import apply_changes, maintain
from ivfspark.sources.collections import table
from ivfspark.sources.index import open_index

#: Ids of vectors that come from events begin here.
NEW_IDS = 1_000_000_000
EVENT_SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_changes(events: DataFrame, vectors: DataFrame, n_vectors: int) -> DataFrame:
    """Update stream of the events table: signup, purchase and view upsert the user's vector, error deletes
    it; click is a query and no change. The vector is a copy, under an id of its own, of the one numbered
    event_id modulo their number; seq is event_id + 1, later than any row of a fresh index."""
    op = F.when(F.col("event_type") == "error", "delete").when(F.col("event_type") != "click", "upsert")
    changes = events.withColumn("op", op).where(F.col("op").isNotNull())
    changes = changes.select(F.col("user_id").alias("asset_id"), (F.col("event_id") + 1).alias("seq"), "op", (F.col("event_id") + NEW_IDS).alias("vec_id"), (F.col("event_id") % n_vectors).alias("copied"))
    copied = vectors.select(F.col("vec_id").alias("copied"), "embedding")
    return changes.join(copied, "copied").select("asset_id", "seq", "op", "vec_id", "embedding")


def stream_updates(
    source: DataFrame, spark: SparkSession, path: str, checkpoint: str, name: str = "updates", every: int = 0, once: bool = True, **limits
) -> StreamingQuery:
    """Apply ``source(asset_id, seq, op, vec_id, embedding)`` to the index at ``path``."""

    def batch(changes: DataFrame, number: int) -> None:
        index = apply_changes(open_index(spark, path), changes, ledger=(name, number))
        if every and number % every == every - 1:
            maintain(index, **limits)

    writer = source.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).queryName(f"{name}-{uuid.uuid4().hex[:8]}")
    writer = writer.trigger(availableNow=True) if once else writer.trigger(processingTime="10 seconds")
    return writer.start()


def read_events(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENT_SCHEMA).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def with_time(events: DataFrame, lateness: str = "1 hour") -> DataFrame:
    """Events with a watermark (which needs an instant, not a local time)."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", lateness)


def tumbling(events: DataFrame, width: str = "1 day") -> DataFrame:
    grouped = events.groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n"))
    return grouped.select(F.col("window.start").alias("w_start"), F.col("window.end").alias("w_end"), "event_type", "n")


def sliding(events: DataFrame, width: str = "2 days", step: str = "1 day") -> DataFrame:
    grouped = events.groupBy(F.window("ts", width, step)).agg(F.count("*").alias("n"))
    return grouped.select(F.col("window.start").alias("w_start"), F.col("window.end").alias("w_end"), "n")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    grouped = events.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return grouped.select(F.col("session_window.start").alias("w_start"), F.col("session_window.end").alias("w_end"), "user_id", "n")


def latest_state(events: DataFrame) -> DataFrame:
    """Stateful latest change of every asset: ``(asset_id, op, seq)``, emitted when it moves forward."""
    import pandas as pd

    def update(key, frames, state):
        best = state.get if state.exists else (-1, "")
        before = best[0]
        for frame in frames:
            row = frame.loc[frame["event_id"].idxmax()]
            if row["event_id"] > best[0]:
                best = (int(row["event_id"]), str(row["event_type"]))
        if best[0] > before:
            state.update(best)
            yield pd.DataFrame({"asset_id": [key[0]], "seq": [best[0]], "event_type": [best[1]]})

    moving = events.where("event_type <> 'click'").select("user_id", "event_id", "event_type")
    return moving.groupBy("user_id").applyInPandasWithState(update, "asset_id long, seq long, event_type string", "seq long, event_type string", "update", "NoTimeout")


def replayed(spark: SparkSession, sf_dir: str, target: str, files: int = 4) -> str:
    """The events table as several files in time order, for a streaming source to read."""
    events = table(spark, sf_dir, "events")
    bounds = events.agg(F.min("event_id").alias("lo"), F.max("event_id").alias("hi")).first()
    step = (bounds.hi - bounds.lo) // files + 1
    for i in range(files):
        lo = bounds.lo + i * step
        events.where((F.col("event_id") >= lo) & (F.col("event_id") < lo + step)).coalesce(1).write.mode("append").parquet(target)
    return target
