"""All queries of the engine by name, with the SQL that checks them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from tracegroup.plans import comparisons, oracles, probes
from tracegroup.plans import queries as plans


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Decisions of the two-stage method over the variants of every document."""
    return plans.two_stage_pipeline(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return plans.queries() | comparisons.queries() | probes.queries()


def oracle_sql() -> dict[str, str]:
    return oracles.oracle_sql() | comparisons.oracle_sql() | probes.oracle_sql()
