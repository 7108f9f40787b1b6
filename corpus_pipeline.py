"""Corpus pipeline: toxicity, line dedup, n-gram Jaccard join, decontamination, mixing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; stages but the last return the columns of
documents.  ``run`` applies them in turn, each result written to the shared folder and read again.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from lowbits.llm import decontam, line_dedup, mixing, ngram_join, toxicity
from lowbits.llm.engine import stored, table


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows that the classifier chain does not reject."""
    return toxicity.accept(docs, toxicity.train(docs, table(spark, sf_dir, "labels")))


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows, without lines that repeat an earlier one up to a word edit."""
    return line_dedup.drop_lines(docs)


def keep_one_per_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The row with the smallest id of each class of near duplicates."""
    return ngram_join.representatives(docs)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows without any window of a benchmark item."""
    return decontam.clean(docs, table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row per document and pass of the temperature mixture, with its text; rows that line dedup emptied are never drawn."""
    return mixing.mix(docs, keep=("text", "lang"))


STAGES = [("toxicity", drop_toxic), ("line dedup", drop_repeated_lines), ("ngram jaccard join", keep_one_per_group), ("decontamination", drop_contaminated), ("mixing", mix_sources)]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir), f"stage-{name.replace(' ', '-')}")
    return STAGES[-1][1](spark, docs, sf_dir)
