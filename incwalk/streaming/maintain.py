"""Streams of edge changes: the walk store follows them batch by batch, and windows count them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from incwalk.plans.update import WalkStore


class Maintainer:
    """Keeps a walk store up with a stream. ``on_batch`` is for ``foreachBatch``.

    The store's manifest, written after all of a batch, names the last batch applied: one that is
    sent again is skipped, by this driver or by another that opened the same folder.
    """

    def __init__(self, store: WalkStore, gate: str | None = None):
        self.store, self.gate = store, gate

    def on_batch(self, changes: DataFrame, batch_id: int) -> None:
        done = self.store.state["batch"]
        if done is None or batch_id > done:
            self.store.apply(changes, gate=self.gate, batch=batch_id)


def maintain_stream(source: DataFrame, state: Maintainer, checkpoint: str):
    """Starts the query; ``source`` streams (op, src, dst, ord)."""
    return source.writeStream.foreachBatch(state.on_batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def windowed_arrivals(events: DataFrame, size: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Arrivals by event type in tumbling or sliding windows; on a stream, rows later than ``late`` drop."""
    rows = events.withWatermark("ts", late) if events.isStreaming else events
    return rows.groupBy(F.window("ts", size, slide) if slide else F.window("ts", size), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str, late: str = "1 hour") -> DataFrame:
    rows = events.withWatermark("ts", late) if events.isStreaming else events
    return rows.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select(F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "user_id", "n")
