"""Exact dedup by a tree-merge of sorted digest runs. DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ldp_hist.llm.shared import ascii_lower, materialise, run_of


def _merge(runs: DataFrame) -> DataFrame:
    """One level: the runs that now share a number are merged, digest by digest.

    The check digest is a binary minimum and maximum, which Spark keeps in a sort-based aggregation: a run
    is read in digest order and merged with the others of its group as one stream.
    """
    return runs.groupBy("run", "digest").agg(
        F.max("best").alias("best"), F.sum("n").alias("n"), F.min("lo").alias("lo"), F.max("hi").alias("hi")
    )


def exact_dedup(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    keep: str = "largest",
    runs: int | None = None,
    fan_in: int = 8,
) -> DataFrame:
    """One row per row of ``docs``: doc_id, keep_id, group_size, kept, text_sha256.

    Texts are equal when identical after lower-casing A-Z; null counts as the empty text. ``keep`` says
    whether the ``largest`` or the ``smallest`` id of equal texts stays. Every partition makes a run of
    its digests, sorted and combined; ``fan_in`` runs at a time merge, level by level, and every level
    retains for each digest the surviving id, the number of rows, and the range of a second digest. If
    that range ever holds two values, two texts share a SHA-256 and the query fails rather than drop one.
    The answer goes back down by (run, digest), so a text shared by a third of all rows meets in no task.

    Null ids never win against others; a group with none but null ids has a null ``keep_id`` and keeps
    its rows. Rows that repeat the winning id are all kept. An empty table gives an empty result; other
    columns are ignored.
    """
    if keep not in ("largest", "smallest"):
        raise ValueError("keep is 'largest' or 'smallest'")
    sign = 1 if keep == "largest" else -1
    text = ascii_lower(F.coalesce(F.col(text_col), F.lit(""))).cast("binary")
    hashed = materialise(
        docs.select(
            F.col(id_col).cast("long").alias("doc_id"),
            F.unhex(F.sha2(text, 256)).alias("digest"),
            F.unhex(F.md5(text)).alias("check"),
            run_of(runs).alias("run"),
        )
    )
    leaf = _merge(
        hashed.select("run", "digest", (F.col("doc_id") * sign).alias("best"), F.lit(1).cast("long").alias("n"),
                      F.col("check").alias("lo"), F.col("check").alias("hi"))
    )
    width = runs or (hashed.agg(F.max("run")).first()[0] or 0) + 1
    top = leaf
    while width > 1:
        top, width = _merge(top.withColumn("run", F.floor(F.col("run") / fan_in).cast("int"))), -(-width // fan_in)
    verified = F.when(F.col("lo") == F.col("hi"), F.col("best") * sign).otherwise(
        F.raise_error(F.lit("two texts share a SHA-256 digest"))
    )
    top = top.select("digest", verified.alias("keep_id"), F.col("n").alias("group_size"))
    down = leaf.select("run", "digest").join(top, "digest")
    return hashed.join(down, ["run", "digest"]).select(
        "doc_id",
        "keep_id",
        "group_size",
        F.coalesce(F.col("doc_id") == F.col("keep_id"), F.col("keep_id").isNull()).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )
