"""Time-ordered replay: each test report is scored against earlier reports, categories by their best member."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tracegroup.operators import grid
from tracegroup.operators.baselines import Scorer, traces_of
from tracegroup.operators.chronology import index_entries, queries_of


def earlier_pairs(queries: DataFrame, scored: DataFrame, entries: DataFrame) -> DataFrame:
    """(query_seq, category_id, cand_seq, score): scored traces as index entries that arrived before the query."""
    q = queries.select(F.col("arrival_seq").alias("query_seq"), F.col("fp").alias("q_fp"))
    e = entries.select(F.col("fp").alias("c_fp"), "category_id", F.col("first_seq").alias("cand_seq"))
    return q.join(scored, "q_fp").join(e, "c_fp").where("cand_seq < query_seq").select("query_seq", "category_id", "cand_seq", F.round("score", 9).alias("score"))


def category_scores(pairs: DataFrame) -> DataFrame:
    """(query_seq, category_id, score, cand_seq): a category's similarity is that of its most similar member; of equal ones the earliest."""
    return pairs.groupBy("query_seq", "category_id").agg(F.max("score").alias("score"), F.max_by("cand_seq", F.struct("score", -F.col("cand_seq"))).alias("cand_seq"))


def ranked(categories: DataFrame) -> DataFrame:
    """Categories per query by score, then by the earliest best member, then by name."""
    w = Window.partitionBy("query_seq").orderBy(F.desc("score"), "cand_seq", "category_id")
    return categories.withColumn("rank", F.row_number().over(w))


def outcomes(queries: DataFrame, ranked_categories: DataFrame) -> DataFrame:
    """Per query: true category, is_new, the predicted category and score (0 without candidates), and the true category's rank."""
    q = queries.select(F.col("arrival_seq").alias("query_seq"), F.col("category_id").alias("true_category"), "is_new")
    best = ranked_categories.where("rank = 1").select("query_seq", F.col("category_id").alias("predicted"), "score", F.col("cand_seq").alias("best_cand"))
    own = ranked_categories.select("query_seq", F.col("category_id").alias("true_category"), F.col("rank").alias("true_rank"))
    told = q.join(best, "query_seq", "left").join(own, ["query_seq", "true_category"], "left")
    return told.select("query_seq", "true_category", "is_new", "predicted", F.coalesce("score", F.lit(0.0)).alias("score"), "best_cand", "true_rank", F.coalesce(F.col("predicted") == F.col("true_category"), F.lit(False)).alias("correct"))


def run(reports: DataFrame, scorer: Scorer, part: str = "test", skip_identical: bool = True, ranks: bool = True, frames: DataFrame | None = None) -> DataFrame:
    """Outcomes of a scorer over a part. Scores are worked out once per pair of distinct traces, inside the tasks where the scorer allows it."""
    if grid.kernel_of(scorer) is not None:
        return grid.outcomes(reports, {"": scorer}, part, skip_identical, ranks, frames).drop("system")
    queries = queries_of(reports, part, skip_identical)
    pairs = scorer(traces_of(queries), traces_of(reports))
    return outcomes(queries, ranked(category_scores(earlier_pairs(queries, pairs, index_entries(reports)))))
