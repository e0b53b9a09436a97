"""All queries of the library and their SQL twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from sparkverdict import decisions, experiments, trials
from sparkverdict.operators import relational


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return experiments.queries() | decisions.queries() | trials.queries() | relational.queries()


def oracle_sql() -> dict[str, str]:
    return experiments.oracle_sql() | decisions.oracle_sql() | trials.oracle_sql() | relational.oracle_sql()


def entry_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Does every source have at least two long documents?"""
    return experiments.queries()["claim_c08"](spark, sf_dir)
