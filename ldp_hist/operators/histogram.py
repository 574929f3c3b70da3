"""Reading succinct histograms: top items, look-ups, filters, set operations, publication over time."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def top_k(hist: DataFrame, k: int) -> DataFrame:
    """The k greatest estimates, ties by item, with their rank: a top-k, not a sort of all."""
    top = hist.orderBy(F.desc("est"), "item").limit(k)
    return top.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("est"), "item")))


def frequency_of(hist: DataFrame, items: DataFrame) -> DataFrame:
    """Estimates of the asked items; what isn't listed is estimated at zero."""
    return items.select("item").join(hist.select("item", "est"), "item", "left").select("item", F.coalesce("est", F.lit(0.0)).alias("est"))


def filter_known(hist: DataFrame, dictionary: DataFrame) -> DataFrame:
    """Domain knowledge removes false positives: listed items that the dictionary has."""
    return hist.join(dictionary.select("item"), "item", "left_semi")


def new_items(hist: DataFrame, dictionary: DataFrame) -> DataFrame:
    """Listed items that the dictionary lacks."""
    return hist.join(dictionary.select("item"), "item", "left_anti")


def stable(first: DataFrame, second: DataFrame) -> DataFrame:
    return first.select("item").intersect(second.select("item"))


def false_positives(hist: DataFrame, heavy: DataFrame) -> DataFrame:
    return hist.select("item").exceptAll(heavy.select("item"))


def union_of_runs(runs: list[DataFrame]) -> DataFrame:
    """Items listed by any run, with their greatest estimate."""
    every = runs[0].select("item", "est")
    for r in runs[1:]:
        every = every.unionByName(r.select("item", "est"))
    return every.groupBy("item").agg(F.max("est").alias("est"))


def as_of(events: DataFrame, published: DataFrame, every: str = "hour") -> DataFrame:
    """Every event with the latest histogram row of its item published at or before it.

    Within an item's ``every`` (an hour, say) a window runs over its events and publications; what was published before
    is carried from a table of the last publication of each item and hour. No task thus holds more than an hour of an item's events.
    """
    period = F.date_trunc(every, "ts")
    both = events.select("event_id", "ts", "item", F.lit(None).cast("double").alias("est"), period.alias("period")).unionByName(
        published.select(F.lit(None).cast("long").alias("event_id"), "ts", "item", "est", period.alias("period")))
    inside = Window.partitionBy("item", "period").orderBy("ts", F.col("event_id").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0)
    last = both.groupBy("item", "period").agg(F.max_by("est", F.when(F.col("event_id").isNull(), F.col("ts"))).alias("last"))
    before = Window.partitionBy("item").orderBy("period").rowsBetween(Window.unboundedPreceding, -1)
    carried = last.select("item", "period", F.last("last", ignorenulls=True).over(before).alias("carried"))
    latest = both.withColumn("latest", F.last("est", ignorenulls=True).over(inside)).where("event_id IS NOT NULL")
    return latest.join(carried, ["item", "period"]).select("event_id", "item", F.coalesce("latest", "carried").alias("est"))


def range_join(values: DataFrame, bands: DataFrame, step: float) -> DataFrame:
    """``values`` (value, ...) with the band (low, high, name) that holds each, as an equality join.

    Values and bands are dealt to cells of width ``step``, a band to each cell that it touches, so no value meets all bands.
    """
    cell = F.floor(F.col("value") / step)
    spread = bands.select("*", F.explode(F.sequence(F.floor(F.col("low") / step), F.floor(F.col("high") / step))).alias("cell"))
    return values.withColumn("cell", cell).join(spread, "cell").where((F.col("value") >= F.col("low")) & (F.col("value") < F.col("high"))).drop("cell")


def drift(published: DataFrame) -> DataFrame:
    """(item, ts, est, change): each publication of an item against the one before."""
    return published.select("item", "ts", "est", (F.col("est") - F.lag("est").over(Window.partitionBy("item").orderBy("ts"))).alias("change"))


def cumulative_share(hist: DataFrame) -> DataFrame:
    """(rank, item, est, share) of a list: which part of its total the items up to each rank have. A list is short by its bounds."""
    order = Window.orderBy(F.desc("est"), "item")
    running = F.sum("est").over(order.rowsBetween(Window.unboundedPreceding, 0)) / F.sum("est").over(Window.partitionBy())
    return hist.select(F.row_number().over(order).alias("rank"), "item", "est", F.round(running, 6).alias("share"))


def moving_counts(published: DataFrame, hours: int) -> DataFrame:
    """(item, ts, est, recent): the sum of an item's estimates over the last ``hours``, its own included."""
    at = F.unix_timestamp("ts")
    recent = Window.partitionBy("item").orderBy(at).rangeBetween(-3600 * hours + 1, 0)
    return published.select("item", "ts", "est", F.sum("est").over(recent).alias("recent"))


def merged_truth(truth: DataFrame, hist: DataFrame) -> DataFrame:
    """(item, f, est) by a sort-merge join: where truth and list are both too long to be sent around."""
    return truth.hint("merge").join(hist, "item", "full").select("item", F.coalesce("f", F.lit(0)).alias("f"), F.coalesce("est", F.lit(0.0)).alias("est"))
