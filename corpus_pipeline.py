"""The training-data pipeline: rules, near duplicates, personal data, mixing, packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns of
documents. The mixing stage decides the order of rows: it writes them in the mixture's order, and packing takes
them in the order in which they lie in its input's files.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from twoview.llm.base import table, written
from twoview.llm.mixing import mix_sources
from twoview.llm.ngram_join import one_of_each
from twoview.llm.packing import pack_documents
from twoview.llm.private_data import masked
from twoview.llm.quality_rules import kept_documents


def rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that fail the base rules or that the isolation forest sets apart.

    Each row is judged by its own text: null and empty texts go, rows without id or of equal ids are told apart.
    """
    return kept_documents(docs, table(spark, sf_dir, "labels"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document of the smallest id of each group of near duplicates; texts without words stay.

    Where ids are missing or repeated, every row is a document by itself, and the first row of a group stays.
    """
    return one_of_each(docs)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replaces personal data of every row by its kind, and sets n_chars anew; null texts stay null."""
    hidden = masked(docs)
    return hidden.withColumn("n_chars", F.length("text").cast("bigint")).select(*docs.columns) if "n_chars" in docs.columns else hidden


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Puts all rows in the order of the mixture of sources."""
    return mix_sources(docs).orderBy("slot", "place").select(*docs.columns)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs texts into batches, in the order in which they lie in the files of docs."""
    try:
        lines = docs.select("doc_id", "text", "_metadata.file_name", "_metadata.row_index")
    except Exception as e:  # docs of no files, as in tests, have no order of their own
        if "_metadata" not in str(e):
            raise
        return pack_documents(docs)
    part = F.regexp_extract("file_name", r"part-([0-9]+)", 1)
    at = F.coalesce(F.try_to_number(part, F.lit("9999999999")).cast("bigint"), F.lit(0)) * (1 << 36) + F.col("row_index")
    return pack_documents(lines.select("doc_id", "text", at.alias("at")), order="at")


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality_rules", rules),
    ("ngram_jaccard_join", near_duplicates),
    ("private_data", personal_data),
    ("mixing", mixing),
    ("packing", packing),
]

#: SQL can't express the isolation forest; the stages are tested against brute-force versions.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on the documents table; each is written as Parquet and read again."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
