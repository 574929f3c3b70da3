"""Helpers of the pipeline operators: shared storage, text folding, runs, graph components.

*Runs.* A key may be shared by a third of all rows. Wherever rows have to meet by such a key, the partition that
read them is their run; what is computed for a key is then looked up by (run, key), so that no task ever holds more
of a hot key than a reading task had. There are as many runs as partitions, so they grow with the input.
"""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

ASCII_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
ASCII_SPACE = " \t\n\x0b\x0c\r"

_own_dir: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir`` of the session.

    Where it is unset a temporary folder stands in, but only in local mode, where one machine does all.
    """
    configured = spark.conf.get("spark.checkpoint.dir", None)
    if configured:
        return configured.rstrip("/")
    if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
        raise ValueError("spark.checkpoint.dir has to name a folder that all executors share")
    if "dir" not in _own_dir:
        _own_dir["dir"] = tempfile.mkdtemp(prefix="ldp_hist_")
        atexit.register(shutil.rmtree, _own_dir["dir"], ignore_errors=True)
    return "file://" + _own_dir["dir"]


def materialise(df: DataFrame) -> DataFrame:
    """Writes ``df`` to the shared folder once and reads it back, which cuts the lineage.

    A lost executor costs a re-read of the table, not a recomputation, and values such as
    ``spark_partition_id()`` are fixed from here on. The files go when the driver's JVM ends.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/ldp_hist-{uuid.uuid4().hex}"
    df.write.parquet(path)
    jvm_path = spark._jvm.org.apache.hadoop.fs.Path(path)
    jvm_path.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(jvm_path)
    return spark.read.schema(df.schema).parquet(path)


def ascii_lower(text: Column) -> Column:
    """Lower-cases A-Z only; the fast path is for texts of one byte a character."""
    return F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(
        F.translate(text, ASCII_UPPER, ASCII_UPPER.lower())
    )


def digest16(text: Column) -> Column:
    """The first 128 bits of SHA-256, as binary."""
    return F.unhex(F.substring(F.sha2(text.cast("binary"), 256), 1, 32))


def packed(docs: DataFrame) -> DataFrame:
    """All columns of ``docs`` as one struct ``row``, so that no name of theirs can clash with ours."""
    return docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))


def identified(docs: DataFrame) -> DataFrame:
    """``row`` (all columns of ``docs``) and ``row_key``, which tells rows apart that have the same id and text.

    It is a hash of where the row is stored, so every scan gives a row the same one; rows that no file holds are written to one first.
    """
    def keyed(df: DataFrame) -> DataFrame:
        row = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")
        return df.select(row, F.xxhash64("_metadata.file_path", "_metadata.row_index").alias("row_key"))

    try:
        return keyed(docs)
    except AnalysisException:
        return keyed(materialise(docs))


def unpacked(df: DataFrame, columns: list[str], **replaced: Column) -> DataFrame:
    """The columns of ``row`` again, those named in ``replaced`` with new values."""
    return df.select(*[replaced.get(c, F.col("row").getField(c)).alias(c) for c in columns])


def run_of(runs: int | None = None) -> Column:
    """The run of a row: the partition that reads it, modulo ``runs`` if given. Fix it with ``materialise`` before using it twice."""
    return F.spark_partition_id() if runs is None else F.pmod(F.spark_partition_id(), F.lit(runs)).cast("int")


def connected_components(edges: DataFrame) -> DataFrame:
    """(node, root) for every node of ``edges`` (u, v: long); the root is the component's smallest node.

    Alternating star contraction: every round points the larger neighbours of a node, then the smaller
    ones, to the least of its neighbourhood. All rounds are joins and aggregations with map-side
    combination; the driver sees two numbers a round. A hub's rows are narrow, and the adaptive join splits them. Self-loops and repeated edges are allowed.
    """
    now = materialise(
        edges.where("u != v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    )
    seen = None
    while True:
        count, total = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if not count or (count, total) == seen:
            return now.select(F.col("u").alias("node"), F.col("v").alias("root")).union(
                now.select(F.col("v"), F.col("v")).distinct()
            )
        seen = count, total
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u")
        now = materialise(
            small.where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v"))
            .union(small.select("u", F.col("m").alias("v"))).distinct()
        )
