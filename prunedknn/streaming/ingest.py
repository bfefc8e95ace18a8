"""Structured Streaming into an indexed table, and windows over event time."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..manifest import Table
from ..operators import build


class Sink:
    """foreachBatch target: a batch is appended once, however often it is replayed, and its files are
    indexed every index_every batches; until then they are searched whole."""

    def __init__(self, table: Table, index_every: int = 1):
        self.table, self.index_every = table, index_every

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        done = self.table.meta().get("batches", [])
        if batch_id in done or batch.isEmpty():
            return
        # rows and number in one commit: a replay after a crash finds both or neither
        self.table = self.table.append(batch, f"batch-{batch_id}", batches=[*done, batch_id][-1000:])
        if (batch_id + 1) % self.index_every == 0:
            self.table = build.fill_gaps(self.table).table


def ingest(stream: DataFrame, table: Table, checkpoint: str, index_every: int = 1, available_now: bool = True):
    sink = Sink(table, index_every)
    writer = stream.writeStream.foreachBatch(sink).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if available_now else writer).start(), sink


def tumbling(events: DataFrame, width: str = "1 day", late: str = "2 days", exact: str = "decimal(18,4)") -> DataFrame:
    """Counts and sums by window and type; rows later than the watermark are left out in a stream. Values are
    added as decimals, so that a sum does not hang on the order of rows."""
    return (
        events.withWatermark("ts", late).groupBy(F.window("ts", width), "event_type")
        .agg(F.count("*").alias("n"), F.sum(F.col("value").cast(exact)).cast("double").alias("total")).select(F.col("window.start").alias("start"), "event_type", "n", "total")
    )


def sessions(events: DataFrame, gap: str = "6 hours", late: str = "2 days") -> DataFrame:
    return (
        events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
        .select(F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "user_id", "n")
    )


def without_repeats(events: DataFrame, key: str = "event_id", late: str = "2 days") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def split_late(events: DataFrame, limit) -> tuple[DataFrame, DataFrame]:
    """(rows from limit on, rows before it): a side output for what arrives too late."""
    return events.where(F.col("ts") >= F.lit(limit)), events.where(F.col("ts") < F.lit(limit))
