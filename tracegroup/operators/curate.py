"""Curation of report data sets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def reviewed_only(reports: DataFrame, reviewed: DataFrame) -> DataFrame:
    """Reports of categories that were reviewed by hand; reviewed: (category_id)."""
    return reports.join(reviewed.select("category_id").distinct(), "category_id", "left_semi")


def drop_foreign(reports: DataFrame, allowed_prefixes: list[str]) -> DataFrame:
    """Reports all of whose frames begin with one of the allowed prefixes; the rest has third-party frames."""
    known = lambda x: F.array_contains(F.transform(F.array(*[F.lit(p) for p in allowed_prefixes]), lambda p: F.startswith(x, p)), True)
    return reports.where(F.forall("frames", known))


def signature_category(frames: Column, anchor, n: int = 2, sep: str = ">") -> Column:
    """A category from a trace: the first n frames that satisfy `anchor`, joined."""
    return F.array_join(F.slice(F.filter(frames, anchor), 1, n), sep)


def removed_share(before: DataFrame, after: DataFrame) -> DataFrame:
    """How many reports a curation step took away."""
    a = after.agg(F.count("*").alias("kept"))
    return before.agg(F.count("*").alias("reports")).join(F.broadcast(a), F.lit(True)).select("reports", "kept", F.round(1 - F.try_divide(F.col("kept").cast("double"), F.col("reports").cast("double")), 6).alias("removed_share"))
