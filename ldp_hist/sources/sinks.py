"""Where reports, counters and histograms go, and report files as sources."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

REPORTS = "level int, pair int, row long, y1 int, y2 int"


def write_reports(reports: DataFrame, path: str) -> None:
    """One file set of one-bit reports; the items never get here."""
    if {"item", "code"} & set(reports.columns):
        raise ValueError("reports must not carry items")
    reports.write.mode("overwrite").parquet(path)


def read_reports(spark: SparkSession, path: str, form: str = "parquet") -> DataFrame:
    """Parquet, JSON or CSV with a fixed schema: nothing is inferred."""
    reader = spark.read.schema(REPORTS)
    return reader.csv(path, header=True) if form == "csv" else reader.format(form).load(path)


def write_counters(counters: DataFrame, path: str) -> None:
    """Counters partitioned by level, so that each round of the tree reads its own level only."""
    writer = counters.write.mode("overwrite")
    (writer.partitionBy("level") if "level" in counters.columns else writer).parquet(path)


def write_histogram(hist: DataFrame, path: str) -> None:
    hist.coalesce(1).write.mode("overwrite").parquet(path)
