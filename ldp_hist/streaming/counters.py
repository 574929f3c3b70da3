"""Counters over streams: sums of one-bit reports by window, mergeable with any batch."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ldp_hist.operators.sketch_oracle import dictionary_reports
from ldp_hist.plans.params import Params

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def event_population(events: DataFrame, user: str = "event_id") -> DataFrame:
    return events.select(F.col(user).cast("string").alias("user_key"), F.col("event_type").alias("item"), "ts")


def once_per_horizon(events: DataFrame, horizon: str = "1 day") -> DataFrame:
    """A user's first event within the watermark's horizon: every further report would cost budget."""
    return events.withWatermark("ts", horizon).dropDuplicatesWithinWatermark(["user_id"])


def window_of(kind: str) -> Column:
    if kind == "session":
        return F.session_window("ts", "10 minutes")
    return F.window("ts", "1 hour", "30 minutes") if kind == "sliding" else F.window("ts", "1 hour")


def windowed_counters(events: DataFrame, p: Params, kind: str = "tumbling", late: str | None = None, user: str = "event_id") -> DataFrame:
    """(start, pair, row, s) for tumbling, sliding or session windows; the same code for streams and tables.

    Session windows are per pair and row, as the counters are.
    """
    reports = dictionary_reports(event_population(events, user), p)
    if late:
        reports = reports.withWatermark("ts", late)
    sums = reports.groupBy(window_of(kind).alias("w"), "pair", "row").agg(F.sum(F.col("y").cast("long")).alias("s"))
    return sums.select(F.col("w.start").alias("start"), "pair", "row", "s")


def stream_counters(stream: DataFrame, p: Params, path: str, checkpoint: str, late: str = "1 hour", user: str = "event_id"):
    """Starts a query that keeps each micro-batch's counters as a file set of its own, named by the batch.

    A batch that is retried overwrites its own files, so every report is summed once.
    """
    reports = dictionary_reports(event_population(stream, user), p).withWatermark("ts", late)

    def write(batch: DataFrame, batch_id: int) -> None:
        sums = batch.groupBy(F.window("ts", "1 hour").start.alias("start"), "pair", "row").agg(F.sum(F.col("y").cast("long")).alias("s"))
        sums.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return reports.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def merged(parts: DataFrame, keys: list[str]) -> DataFrame:
    """Counters of windows, sites or batches added up: the sketch is linear."""
    return parts.groupBy(*keys).agg(F.sum("s").alias("s"))


def budgeted(stream: DataFrame, eps: float, total: float) -> DataFrame:
    """(user_id, event_type, ts) of the events whose report the user's budget still covers, kept as state by user."""
    schema = "user_id long, event_type string, ts timestamp"

    def spend(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        (spent,) = state.get if state.exists else (0.0,)
        for pdf in batches:
            room = max(0, int((total - spent + 1e-9) / eps))
            taken = pdf.sort_values(["ts", "event_id"]).head(room)
            spent += eps * len(taken)
            yield taken[["user_id", "event_type", "ts"]]
        state.update((spent,))

    return stream.groupBy("user_id").applyInPandasWithState(spend, schema, "spent double", "append", "NoTimeout")
