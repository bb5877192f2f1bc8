"""Streams of new items and engagement: incremental mapping, windows, de-duplication, joins, state, late rows."""

from __future__ import annotations

from collections.abc import Iterator
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from neardup.config import DEFAULT, Config
from neardup.operators import incremental
from neardup.sources.sinks import Snapshots, scratch


def files(spark: SparkSession, path: str, schema, per_trigger: int = 1) -> DataFrame:
    """A stream over Parquet files of a folder, in order of their names' times."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path)


def with_time(df: DataFrame, column: str = "ts", delay: str = "1 day") -> DataFrame:
    """``df`` with its time as TIMESTAMP (watermarks refuse TIMESTAMP_NTZ) and a watermark on it."""
    return df.withColumn(column, F.col(column).cast("timestamp")).withWatermark(column, delay)


def tumbling(df: DataFrame, size: str = "1 day") -> DataFrame:
    """``start, action, events`` by windows of one size."""
    return df.groupBy(F.window("ts", size), "action").agg(F.count("*").alias("events")).select(F.col("window.start").alias("start"), "action", "events")


def sliding(df: DataFrame, size: str = "7 days", step: str = "1 day") -> DataFrame:
    """``start, events`` by overlapping windows."""
    return df.groupBy(F.window("ts", size, step)).agg(F.count("*").alias("events")).select(F.col("window.start").alias("start"), "events")


def sessions(df: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """``user_id, start, events``: runs of a user's events without a longer gap."""
    return df.groupBy("user_id", F.session_window("ts", gap)).agg(F.count("*").alias("events")).select("user_id", F.col("session_window.start").alias("start"), "events")


def exact_once(df: DataFrame, keys: list[str]) -> DataFrame:
    """Rows whose keys were not seen within the watermark's delay."""
    return df.dropDuplicatesWithinWatermark(keys)


def engaged(arrivals: DataFrame, bookmarks: DataFrame, within: str = "1 day") -> DataFrame:
    """Stream-stream join: engagement with an item up to ``within`` after its arrival. Both sides need watermarks."""
    b = bookmarks.select(F.col("item_id").alias("b_item"), F.col("ts").alias("b_ts"), "event_id")
    near = (F.col("item_id") == F.col("b_item")) & (F.col("b_ts") >= F.col("ts")) & (F.col("b_ts") <= F.col("ts") + F.expr(f"interval {within}"))
    return arrivals.join(b, near).select("item_id", "event_id")


class ClusterCounter(StatefulProcessor):
    """Events per cluster so far; in event time a count ends a day after its last event."""

    QUIET_MS = 86_400_000

    def __init__(self, timed: bool = False):
        self.timed = timed

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.count = handle.getValueState("count", "n long")

    def handleInputRows(self, key: Any, rows: Iterator[pd.DataFrame], timerValues: Any) -> Iterator[pd.DataFrame]:
        n, last = self.count.get()[0] if self.count.exists() else 0, 0
        for r in rows:
            n += len(r)
            last = max(last, int(r["ts"].max().timestamp() * 1000))
        self.count.update((n,))
        if self.timed:
            for t in list(self.handle.listTimers()):
                self.handle.deleteTimer(t)
            self.handle.registerTimer(last + self.QUIET_MS)
        yield pd.DataFrame({"head_id": [key[0]], "events": [n]})

    def handleExpiredTimer(self, key: Any, timerValues: Any, expiredTimerInfo: Any) -> Iterator[pd.DataFrame]:
        self.count.clear()
        yield pd.DataFrame({"head_id": [], "events": []}).astype("int64")

    def close(self) -> None:
        pass


def cluster_counts(df: DataFrame, timed: bool = False) -> DataFrame:
    """Running counts ``(head_id, events)`` of a stream with ``head_id`` and ``ts``. Needs the RocksDB state store.

    ``timed`` ends quiet counts by event-time timers and needs a watermark.
    """
    return df.groupBy("head_id").transformWithStateInPandas(
        statefulProcessor=ClusterCounter(timed), outputStructType="head_id long, events long",
        outputMode="Update", timeMode="EventTime" if timed else "None",
    )


def batch_writer(store: Snapshots, items: Snapshots, cfg: Config = DEFAULT):
    """For ``foreachBatch``: applies a micro-batch ``(item_id, words)`` to the mapping, once for each batch id.

    ``items`` keeps the bits of all items so far; both tables move by whole versions.
    """

    def apply(batch: DataFrame, batch_id: int) -> None:
        new = batch.select("item_id", "words").dropDuplicates(["item_id"])
        first = store.version() < 0
        old = None if items.version() < 0 else items.read()
        mapping = None if first else store.read().select("item_id", "head_id", "score_to_head")
        known = old if old is not None else new.limit(0)
        if mapping is not None:  # a replay after the items were written: only rows of the mapping count as old
            known = known.join(mapping.select("item_id"), "item_id", "left_semi")
        after = incremental.apply_batch(mapping, known, new, cfg)
        if store.commit(after, batch_id):
            items.commit(known.unionByName(new.join(known, "item_id", "left_anti")), batch_id)

    return apply


def run_available(stream: DataFrame, out, mode: str = "append") -> None:
    """Runs a stream over all that is there, into ``foreachBatch(out)``, and waits for its end."""
    q = stream.writeStream.outputMode(mode).foreachBatch(out).option("checkpointLocation", scratch(stream.sparkSession)).trigger(availableNow=True).start()
    q.awaitTermination()


def collected(stream: DataFrame, mode: str = "append") -> tuple[DataFrame, list[dict]]:
    """All rows that a stream writes, as a table in the shared folder, and its progress reports."""
    spark = stream.sparkSession
    path = scratch(spark)

    def out(batch: DataFrame, batch_id: int) -> None:
        batch.withColumn("batch_id", F.lit(batch_id).cast("long")).write.mode("append").parquet(path)

    q = stream.writeStream.outputMode(mode).foreachBatch(out).option("checkpointLocation", scratch(spark)).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(path), [dict(p) for p in q.recentProgress]


def dropped_rows(progress: list[dict]) -> int:
    """Rows dropped as late by the watermark."""
    return sum(o.get("numRowsDroppedByWatermark", 0) for p in progress for o in p["stateOperators"])
