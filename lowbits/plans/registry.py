"""Every registered query and its SQL twin."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import exp_queries, rel_queries, set_queries, stream_queries, theory_queries

PARTS = (theory_queries, set_queries, exp_queries, rel_queries, stream_queries)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One-bit estimates of all pairs of documents over 0.3, next to their exact resemblance."""
    return set_queries.QUERIES["est_low_b1_docs"](spark, sf_dir).orderBy(F.desc("r_hat"), "id_l", "id_r")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: f for part in PARTS for name, f in part.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for part in PARTS for name, sql in part.ORACLES.items()}
