"""Streaming: a loop that keeps the fresh sample, a loop that refreshes the view, and window operators.

State of the loops is the change log and the versions of the catalogue, not operator
state; a late row is an ordinary insert of the next batch. Only window aggregates use
watermarks.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..catalog import ViewManager
from ..functions.hashing import key_hash_filter
from ..sources.changes import ChangeSet


class FreshSampleLoop:
    """Appends each batch to the change log and publishes a fresh sample every ``every`` batches.

    The log has a directory a batch; the catalogue's entry knows the last batch that a
    full refresh has taken in, so what is pending are the later ones.
    """

    def __init__(self, manager: ViewManager, view: str, table: str, base: DataFrame, log: str, every: int = 1) -> None:
        self.manager, self.view, self.table, self.base, self.log, self.every = manager, view, table, base, log, every

    def pending(self) -> ChangeSet:
        logged = self.manager.spark.read.option("basePath", self.log).parquet(self.log)
        applied = self.manager.entries[self.view].applied
        columns = self.base.columns
        old = self.base.unionByName(logged.filter(F.col("batch_id") <= applied).select(*columns))
        return ChangeSet({self.table: old}, {self.table: logged.filter(F.col("batch_id") > applied).select(*columns)}, keys={self.table: ()})

    def keep(self, batch: DataFrame, batch_id: int) -> None:
        # a batch that is tried again overwrites its own rows
        batch.select(*self.base.columns).write.mode("overwrite").parquet(f"{self.log}/batch_id={batch_id}")

    def on_batch(self, batch: DataFrame, batch_id: int) -> None:
        self.keep(batch, batch_id)
        if (batch_id + 1) % self.every == 0:
            self.manager.apply(self.view, self.pending())

    def start(self, stream: DataFrame, checkpoint: str, once: bool = True):
        writer = stream.writeStream.foreachBatch(self.on_batch).option("checkpointLocation", checkpoint)
        return (writer.trigger(availableNow=True) if once else writer).start()


class RefreshLoop(FreshSampleLoop):
    """Refreshes the whole view every ``every`` batches."""

    def on_batch(self, batch: DataFrame, batch_id: int) -> None:
        self.keep(batch, batch_id)
        entry = self.manager.entries[self.view]
        if (batch_id + 1) % self.every == 0 and batch_id > entry.applied:
            entry.pending = [self.pending()]
            # the pointer of the new version names the batch, so a restart neither repeats nor skips it
            self.manager.refresh(self.view, applied=batch_id)


def tumbling(events: DataFrame, width: str = "1 hour", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", width), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))


def sliding(events: DataFrame, width: str = "1 hour", slide: str = "15 minutes", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", width, slide), "event_type").agg(F.count(F.lit(1)).alias("n"))


def sessions(events: DataFrame, gap: str = "12 hours", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))


def distinct_events(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def sampled_counts(events: DataFrame, m: float, salt: str = "s1") -> DataFrame:
    """A stateful count by user that holds state for sampled users only."""
    return key_hash_filter(events, ["user_id"], m, salt).groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))
