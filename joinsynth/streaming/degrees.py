"""Streaming ingestion of event tables into windowed frequency tables and degrees.

A release is one-shot; a stream is released on a fixed public schedule with one slice of the budget
for each firing (:func:`release_on_schedule`).
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..ledger import Ledger
from ..sources.formats import shared_folder

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def read_events(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    """Events arriving as Parquet files in a folder (``events*.parquet``)."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", "events*.parquet").parquet(folder)


def tumbling(events: DataFrame, width: str = "1 day", late: str = "2 hours") -> DataFrame:
    """Frequency table of (window, event type)."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("freq")).select(F.col("w.start").alias("start"), "event_type", "freq")


def sliding(events: DataFrame, width: str = "1 day", step: str = "12 hours", late: str = "2 hours") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", width, step).alias("w")).agg(F.count("*").alias("freq")).select(F.col("w.start").alias("start"), "freq")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    """Sessions of a user: (user, start, number of events)."""
    return events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("freq")).select("user_id", F.col("w.start").alias("start"), "freq")


def dedup(events: DataFrame, late: str = "1 day") -> DataFrame:
    """Each event id once, within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def click_to_purchase(events: DataFrame, within: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """Stream-stream interval join: purchases of a user at most ``within`` after a click."""
    clicks = events.filter("event_type = 'click'").select(F.col("user_id").alias("u"), F.col("event_id").alias("click_id"), F.col("ts").alias("click_ts")).withWatermark("click_ts", late)
    buys = events.filter("event_type = 'purchase'").select("user_id", F.col("event_id").alias("buy_id"), F.col("ts").alias("buy_ts")).withWatermark("buy_ts", late)
    on = F.expr(f"u = user_id and buy_ts >= click_ts and buy_ts <= click_ts + interval {within}")
    return clicks.join(buys, on).select("user_id", "click_id", "buy_id")


def with_segment(events: DataFrame, customers: DataFrame) -> DataFrame:
    """Stream-static join with the customer table."""
    return events.join(customers.select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id")


def capped_degrees(events: DataFrame, cap: int) -> DataFrame:
    """(user, degree so far, at most ``cap``) by a stateful operator: bounds what one user can add to a later release."""

    def update(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        seen = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((min(cap, seen),))
        yield pd.DataFrame({"user_id": [key[0]], "degree": [min(cap, seen)]})

    return events.groupBy("user_id").applyInPandasWithState(update, "user_id bigint, degree bigint", "seen bigint", "update", "NoTimeout")


def run_available(stream: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Runs a stream over all available files and returns its result, written as Parquet to the shared folder: no row of it passes the driver.

    Each micro-batch has a folder of its own, so one that is repeated replaces what it wrote; in complete mode only the last counts, and two are kept.
    """
    folder, numbers = shared_folder(stream.sparkSession), []

    def write(batch: DataFrame, number: int) -> None:
        place = number % 2 if mode == "complete" else number
        batch.write.mode("overwrite").parquet(f"{folder}/{place}")
        numbers.append(place)

    writer = stream.writeStream.foreachBatch(write).queryName(name).outputMode(mode).trigger(availableNow=True)
    if checkpoint:
        writer = writer.option("checkpointLocation", checkpoint)
    writer.start().awaitTermination()
    places = numbers[-1:] if mode == "complete" else sorted(set(numbers))
    if not places:
        return stream.sparkSession.createDataFrame([], stream.schema)
    return stream.sparkSession.read.schema(stream.schema).parquet(*(f"{folder}/{p}" for p in places))


def release_on_schedule(stream: DataFrame, firings: int, eps: float, delta: float, release: Callable[[DataFrame, float, float, int], None], checkpoint: str) -> Ledger:
    """One release for each of a public number of micro-batches; the budget is divided up front, later batches get nothing."""
    ledger = Ledger(eps, delta)

    def fire(batch: DataFrame, number: int) -> None:
        if number < firings:
            ledger.spend(f"firing {number}", eps / firings, delta / firings)
            release(batch, eps / firings, delta / firings, number)

    stream.writeStream.foreachBatch(fire).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return ledger
