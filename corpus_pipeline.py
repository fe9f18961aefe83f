"""From raw documents to packed training sequences, a stage at a time."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from runjoin.llm.common import Scratch, table
from runjoin.llm.exact_dedup import drop_exact_copies
from runjoin.llm.factor_machine import keep_good
from runjoin.llm.near_dedup import drop_near_copies
from runjoin.llm.packing import pack
from runjoin.llm.quality_rules import keep_ruled, trusted_of


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rules keep, all columns, rows as they are.

    Null and empty texts go (fewer than 50 words); each of repeated rows is judged alone and alike; a null doc_id is never
    trusted; without labels only the counts decide; an empty table stays empty; extra columns come along.
    """
    return keep_ruled(docs, trusted_of(table(spark, sf_dir, "labels", "doc_id", "quality")))


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the factorisation machine, fitted on labelled ones outside the held-out fold, scores 0.3 or more.

    A null text counts as empty and is scored, a null n_chars as 0; repeated rows score alike; a null doc_id is never
    fitted on; without labels every score is one half, so all stay; an empty table stays empty; extra columns come along.
    """
    return keep_good(docs, table(spark, sf_dir, "labels", "doc_id", "quality"))


def exact_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of every group of equal texts: the longest, then of the smallest doc_id, then by its columns.

    Groups go by text alone: rows of one doc_id (or none) with different texts all stay. Null and empty texts are one group;
    an empty table stays empty; extra columns come along, whatever their names.
    """
    return drop_exact_copies(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of every group of near duplicates (runs of five words, 0.8): of the smallest doc_id, then the first.

    Groups go by rows: unlike texts under one doc_id (or none) stay. Rows without words all stay; an empty table stays
    empty; extra columns come along, whatever their names.
    """
    return drop_near_copies(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of sequences of at most 1024 ids: every id of every row, and its end, lies in one piece.

    A null or empty text is its end alone; repeated rows are packed each; null ids stay null; an empty table gives none.
    """
    return pack(docs)


STAGES = [
    ("quality_rules", quality_rules),
    ("quality_classifier", quality_classifier),
    ("exact_dedup", exact_dedup),
    ("near_dedup", near_dedup),
    ("packing", packing),
]

#: The classifier's trained scores can't be written in SQL; tests/llm holds every stage's rows against plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Apply all stages to the documents of a folder, each written to the shared folder and read again.

    Null and empty texts go with the first stage (they have fewer than 50 words); an empty table passes through.
    """
    scratch = Scratch(spark, "pipeline")
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = scratch.save(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
