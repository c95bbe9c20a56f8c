"""Corpus pipeline: language ID, near-dedup, substring dedup, mixing, piece encoding, each over all rows that its predecessor kept.

Every stage takes (spark, docs, sf_dir) and gives a DataFrame that is written as Parquet and read again as the next stage's ``docs``. All
but the last return the columns of ``documents``; an empty table passes through as an empty one.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tracelink.llm import language_crf, near_dups, pieces, poisson_mix, windows
from tracelink.llm.common import bounded_batches, materialise, table

#: A document is rejected only without letters, or if no language has at least this mean marginal.
LEAST_LANGUAGE_SCORE = 0.3
PERCENT_ALIKE = 80


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents without letters or of no clear language; a null language is filled with the predicted one."""
    bounded_batches(spark)
    found = language_crf.identified(docs, language_crf.train(docs))
    clear = found.where((F.col("lang_pred") != language_crf.UNKNOWN) & (F.col("lang_score") >= LEAST_LANGUAGE_SCORE))
    return clear.withColumn("lang", F.coalesce("lang", "lang_pred")).select(*docs.columns)


def near_dup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep one document of each group of near duplicates."""
    bounded_batches(spark)
    return near_dups.deduplicated(docs, percent=PERCENT_ALIKE).select(*docs.columns)


def substring_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Remove words of passages that a document with a smaller id has too; every document stays, ``n_chars`` follows."""
    bounded_batches(spark)
    return windows.drop_repeats(docs).withColumn("n_chars", F.length("text").cast("long")).select(*docs.columns)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeat documents by Poisson counts towards tempered source weights, and shuffle."""
    return poisson_mix.poisson_mix(docs).select(*docs.columns)


def piece_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Encode texts; adds ``pieces`` and ``n_pieces``."""
    bounded_batches(spark)
    return pieces.encoded(docs, pieces.PieceModel.load(pieces.DEFAULT_MODEL))


STAGES = [
    ("language_id", language_stage),
    ("near_dedup", near_dup_stage),
    ("substring_dedup", substring_stage),
    ("mixing", mixing_stage),
    ("pieces", piece_stage),
]

#: The learned first stage has no SQL form; tests/llm compares the stages with brute-force versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
