"""The final decision: attach to the best candidate's category or open a new one."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tracegroup.operators.components import resolve_roots


def calibrated(score: Column, stage: str) -> Column:
    """Scores between 0 and 1: the logistic function of a reranker's score, half of 1 + cosine of an embedding's."""
    return F.when(F.lit(stage) == "rerank", 1 / (1 + F.exp(-score))).otherwise((1 + score) / 2)


def decide(outcomes: DataFrame, thresholds: DataFrame) -> DataFrame:
    """outcomes with action: attach if the score is larger than the threshold, else create; `thresholds` is one row."""
    t = thresholds.select(F.col("threshold").alias("t"))
    told = outcomes.join(F.broadcast(t), F.lit(True))
    attach = F.col("predicted").isNotNull() & (F.col("score") > F.coalesce("t", F.lit(0.0)))
    return told.withColumn("action", F.when(attach, "attach").otherwise("create")).drop("t")


def assign(decisions: DataFrame, reports: DataFrame) -> DataFrame:
    """(query_seq, category_id): the known category of the report that a chain of attachments ends in, or the report's own number."""
    parents = decisions.select(F.col("query_seq").alias("report"), F.when(F.col("action") == "attach", F.col("best_cand")).alias("parent"))
    roots = resolve_roots(parents)
    known = reports.select(F.col("arrival_seq").alias("root"), "category_id")
    known = known.join(parents.select(F.col("report").alias("root")), "root", "left_anti")
    return roots.join(known, "root", "left").select(F.col("report").alias("query_seq"), F.coalesce("category_id", F.concat(F.lit("new:"), F.col("root").cast("string"))).alias("category_id"))
