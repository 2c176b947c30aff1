"""Registry of the queries over the sketches and of their SQL twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from rotahash.plans import app_queries, operator_queries, sketch_queries

MODULES = (sketch_queries, app_queries, operator_queries)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Estimates of word pairs from rotating binned MinHash with a hashed split."""
    return sketch_queries.QUERIES["estimate_word_pairs_rotbin_2u"](spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: v for m in MODULES for k, v in m.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {k: v for m in MODULES for k, v in m.SQL.items()}
