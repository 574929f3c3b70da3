"""Line dedup: hashes of lines in range partitions, per-document bitmaps back. DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ldp_hist.llm.shared import ASCII_SPACE, ascii_lower, digest16, materialise, packed, run_of, unpacked

WORD_BITS = 62


def split_lines(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def line_keys(text: Column) -> Column:
    """A line's key, hashed to 128 bits; null for a line whose key is empty is left to the caller's length."""
    return F.transform(split_lines(text), lambda line: ascii_lower(F.trim(line, F.lit(ASCII_SPACE))))


def drop_bitmaps(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    min_chars: int = 1,
    min_docs: int = 10,
    keep_first: bool = False,
    runs: int | None = None,
) -> DataFrame:
    """(doc_id, text_hash, words): the lines each document loses, as a sparse bitmap.

    ``words`` maps a word number to 62 bits, bit i of word w standing for line 62*w+i; words without a bit
    and documents without a dropped line are left out. A key of at least ``min_chars`` code points
    that ``min_docs`` documents or more hold loses its lines; with ``keep_first`` its first line, by
    document id (null first) and position, stays.

    A row names each of its keys once, repeated rows too; per run the keys are counted with their first occurrence,
    and those few rows are range-partitioned by key with document and position as the secondary sort: a
    window streams over them. A key that a third of all documents hold thus never fills one task.
    """
    hashed = materialise(
        docs.select(
            F.col(id_col).cast("long").alias("doc_id"),
            F.xxhash64(text_col).alias("text_hash"),
            F.transform(
                line_keys(F.col(text_col)), lambda k: F.when(F.char_length(k) >= min_chars, digest16(k))
            ).alias("keys"),
            run_of(runs).alias("run"),
        )
    )
    no_first = F.lit(None).cast("struct<doc_id:bigint,text_hash:bigint,pos:int>")
    once = hashed.select("run", F.explode(F.array_distinct("keys")).alias("key"), F.lit(1).alias("n"), no_first.alias("first")).where("key IS NOT NULL")
    if keep_first:
        lines = hashed.select("run", "doc_id", "text_hash", F.posexplode("keys").alias("pos", "key")).where("key IS NOT NULL")
        once = once.union(lines.select("run", "key", F.lit(0), F.struct("doc_id", "text_hash", "pos")))
    per_run = once.groupBy("run", "key").agg(F.sum("n").alias("n"), F.min("first").alias("first"))
    by_key = Window.partitionBy("key")
    counted = (
        per_run.repartitionByRange("key")
        .sortWithinPartitions("key", "first")
        .select("run", "key", F.sum("n").over(by_key).alias("n_docs"), F.min("first").over(by_key).alias("first"))
    )
    heavy = counted.where(F.col("n_docs") >= min_docs).select("run", "key", "first")
    lines = hashed.select("run", "doc_id", "text_hash", F.posexplode("keys").alias("pos", "key")).where("key IS NOT NULL")
    gone = lines.join(heavy, ["run", "key"])
    if keep_first:
        gone = gone.where(~F.col("first").eqNullSafe(F.struct("doc_id", "text_hash", "pos")))
    bit = F.expr(f"shiftleft(1L, pos % {WORD_BITS})")
    return (
        gone.groupBy("doc_id", "text_hash", F.floor(F.col("pos") / WORD_BITS).cast("int").alias("word"))
        .agg(F.bit_or(bit).alias("bits"))
        .groupBy("doc_id", "text_hash")
        .agg(F.map_from_entries(F.collect_list(F.struct("word", "bits"))).alias("words"))
    )


def reduced(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """``row`` (all columns), ``kept_text``, ``n_lines`` and ``n_dropped`` of every row of ``docs``.

    Lines end at \\n; a key is the line without white space (space, \\t to \\r) at its ends, A-Z in lower
    case. Null and empty texts have one empty line, whose key is empty and never dropped. Rows with the
    same id and text share a bitmap; each row counts as a document of its own. A null text stays null.
    """
    maps = drop_bitmaps(docs.select(id_col, text_col), id_col, text_col, **how)
    text = F.col("row").getField(text_col)
    keyed = packed(docs).withColumns({"own_id": F.col("row").getField(id_col).cast("long"), "own_hash": F.xxhash64(text)})
    joined = keyed.join(maps, F.col("own_id").eqNullSafe(F.col("doc_id")) & (F.col("own_hash") == F.col("text_hash")), "left")
    lines = split_lines(text)
    last = F.floor((F.size(lines) - 1) / WORD_BITS).cast("int")
    dense = F.transform(F.sequence(F.lit(0), last), lambda w: F.coalesce(F.element_at("words", w), F.lit(0).cast("long")))
    parts = joined.withColumns({"lines": lines, "dense": F.when(F.col("words").isNotNull(), dense)})

    def stays(line: Column, i: Column) -> Column:
        return F.getbit(F.get("dense", F.floor(i / WORD_BITS).cast("int")), (i % WORD_BITS).cast("int")) == 0

    parts = parts.withColumn("kept", F.when(F.col("words").isNotNull(), F.filter("lines", stays)).otherwise(F.col("lines")))
    n_lines, n_kept = F.size("lines").cast("long"), F.size("kept").cast("long")
    return parts.select(
        "row",
        F.when(F.col("words").isNull(), text).otherwise(F.array_join("kept", "\n")).alias("kept_text"),
        n_lines.alias("n_lines"),
        (n_lines - n_kept).alias("n_dropped"),
    )


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """``docs`` with its columns, the text reduced to the lines that stay; empty tables pass through."""
    return unpacked(reduced(docs, id_col, text_col, **how), docs.columns, **{text_col: F.col("kept_text")})


def line_dedup(docs: DataFrame, **how) -> DataFrame:
    """doc_id, n_lines, n_dropped, kept_sha256 for every document; see ``reduced``."""
    return reduced(docs.select("doc_id", "text"), **how).select(
        F.col("row.doc_id").alias("doc_id"),
        "n_lines",
        "n_dropped",
        F.sha2(F.coalesce(F.col("kept_text"), F.lit("")).cast("binary"), 256).alias("kept_sha256"),
    )
