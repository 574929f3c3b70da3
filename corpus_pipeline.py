"""The corpus pipeline: five operators, each on what the one before it kept.

Every stage takes and (the last one apart) returns the columns of ``documents``, whatever others there are and whatever their names. All
stages pass an empty table on as an empty one, look at whole texts of any length, and treat rows that repeat as rows of their own.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ldp_hist.llm import decontaminate, langid, line_dedup, pieces, shared, simhash


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents without a letter or that neither a language nor all of them in total accept; a kept one without a ``lang`` gets the predicted one.

    Null and empty texts have no letter and go; equal texts share a fate. Without a labelled row nothing can be learned, and nothing stays.
    """
    model = langid.train(docs)
    known = langid.annotate(docs, model).where("accepted")
    return shared.unpacked(known, docs.columns, lang=F.coalesce("row.lang", "lang_pred"))


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of a line of 15 characters or more in ten or more documents only the first occurrence stays, by id (null first), text hash and position.

    Null texts stay null, and the empty line is too short to go. Rows with the same id and text lose the same lines.
    """
    return line_dedup.dedup_lines(docs, min_chars=15, min_docs=10, keep_first=True)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents alike in 0.8 or more of their five-word shingles, or linked by such, the one with the least id stays (null first).

    Of rows with that id the one whose place has the least hash does, so one row of a class is left even where rows repeat. Null texts and texts
    without a word are one class.
    """
    keyed = shared.identified(docs)
    classes = simhash.near_copies(keyed.select("row.doc_id", "row.text", "row_key"))
    gone = classes.where(~(F.col("doc_id").eqNullSafe(F.col("class_id")) & (F.col("row_key") == F.col("class_key")))).select("doc_id", F.col("row_key").alias("gone_key"))
    left = keyed.join(gone, F.col("row.doc_id").eqNullSafe(F.col("doc_id")) & (F.col("row_key") == F.col("gone_key")), "left_anti")
    return shared.unpacked(left, docs.columns)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents with a window that is 0.8 or more alike to a benchmark item; null and empty texts have none and stay."""
    benchmark = spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    found = decontaminate.contamination(docs, benchmark)
    return shared.unpacked(found.where(F.size("item_ids") == 0), docs.columns)


def encode_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, lang, n_tokens, token_ids and round_trip of every document; null and empty texts have no ids."""
    return pieces.encode_documents(docs, carry=["doc_id", "lang"])


STAGES = [
    ("language id", identify_language),
    ("line dedup", drop_repeated_lines),
    ("simhash near-dedup", drop_near_copies),
    ("benchmark decontamination", drop_contaminated),
    ("sentencepiece", encode_pieces),
]

#: Kernel classification, similarity classes and piece scores have no SQL form; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each one's result is written to the shared folder and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES[:-1]:
        docs = shared.materialise(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
