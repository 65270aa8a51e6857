"""The corpus pipeline: quality rules, near duplicates, personal data, mixing, piece encoding.

Each stage takes (spark, docs, sf_dir) and works on all that the stage before kept; run() writes each
stage's rows to the shared folder, reads them again for the next, and deletes what the stage has written
on its way.  All stages but the last return the columns of documents.  Documents in the mix stand once with
the words that the mix takes of them: one taken twice has its text twice, one taken in part that part of it.
Rows without a doc_id, rows that repeat one, empty texts and empty tables pass through as the operators say.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from strata_descent.llm import common, mixing, ngram_join, personal_data, pieces, quality_rules

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules keep."""
    return quality_rules.keep_quality(docs, common.table(spark, sf_dir, "labels"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates: the one of least id."""
    return ngram_join.keep_one(docs)


def personal(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with personal data replaced by its kind."""
    return personal_data.redact(docs)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The words of each document that the mix takes; documents of which it takes none go."""
    return mixing.mixed_texts(docs)


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Piece ids of each text, with its lang and source."""
    return pieces.sample_pieces(docs, "lang", "source")


STAGES: list[tuple[str, Stage]] = [
    ("quality_rules", quality),
    ("ngram_join", near_duplicates),
    ("personal_data", personal),
    ("mixing", mixed),
    ("pieces", encoded),
]
#: The stages' models and hashes have no SQL form; tests hold each stage against a plain version.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        docs = common.saved(stage(spark, docs, sf_dir))
        common.clear(spark, docs)
    return docs
