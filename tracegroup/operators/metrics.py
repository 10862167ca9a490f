"""Measures over outcomes (query_seq, is_new, score, correct, true_rank) and over data sets.

Curves first count outcomes per distinct score, so what a window sorts in one task is the scores, not the reports.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.window import WindowSpec



def _upto() -> WindowSpec:
    return Window.orderBy("score").rowsBetween(Window.unboundedPreceding, Window.currentRow)


def acc_at_1(outcomes: DataFrame) -> DataFrame:
    """Share of attached reports whose top category is right; reports that open categories are left out."""
    return outcomes.agg(F.round(F.avg(F.when(~F.col("is_new"), F.col("correct").cast("double"))), 6).alias("acc_at_1"), F.count(F.when(~F.col("is_new"), 1)).alias("n_attached"), F.count(F.when(F.col("is_new"), 1)).alias("n_new"))


def acc_at_k(outcomes: DataFrame, ks: tuple[int, ...] = (1, 3, 5, 10)) -> DataFrame:
    """Share of attached reports whose category is among the first k, and the mean reciprocal rank."""
    old = outcomes.where(~F.col("is_new"))
    shares = [F.round(F.avg((F.coalesce("true_rank", F.lit(1 << 30)) <= k).cast("double")), 6).alias(f"acc_at_{k}") for k in ks]
    return old.agg(*shares, F.round(F.avg(F.coalesce(1 / F.col("true_rank"), F.lit(0.0))), 6).alias("mrr"))


def _per_score(outcomes: DataFrame) -> DataFrame:
    return outcomes.groupBy("score").agg(F.count(F.when(~F.col("is_new"), 1)).alias("attached"), F.count(F.when(F.col("is_new"), 1)).alias("new"))


def roc_auc(outcomes: DataFrame) -> DataFrame:
    """Probability that an attached report scores above one that opens a category, ties half. Null without both classes."""
    s = _per_score(outcomes).withColumn("below", F.coalesce(F.sum("new").over(Window.orderBy("score").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    both = s.agg(F.sum(F.col("attached") * (F.col("below") + F.col("new") / 2)).alias("u"), F.sum("attached").alias("n_attached"), F.sum("new").alias("n_new"))
    return both.select(F.round(F.try_divide(F.col("u"), F.col("n_attached") * F.col("n_new")), 6).alias("auc"), F.col("n_attached").cast("long"), F.col("n_new").cast("long"))


def roc_points(outcomes: DataFrame) -> DataFrame:
    """(score, tpr, fpr) for creating at or below each score; positive is opening a category."""
    s = _per_score(outcomes)
    whole = s.agg(F.sum("attached").alias("a"), F.sum("new").alias("c"))
    run = s.withColumn("tp", F.sum("new").over(_upto())).withColumn("fp", F.sum("attached").over(_upto()))
    return run.join(F.broadcast(whole), F.lit(True)).select("score", F.round(F.try_divide(F.col("tp").cast("double"), F.col("c").cast("double")), 6).alias("tpr"), F.round(F.try_divide(F.col("fp").cast("double"), F.col("a").cast("double")), 6).alias("fpr"))


def f1_curve(outcomes: DataFrame) -> DataFrame:
    """(threshold, precision, recall, f1) of creating when the score is at most the threshold, over the scores that occur."""
    s = _per_score(outcomes)
    whole = s.agg(F.sum("new").alias("c"))
    run = s.withColumn("tp", F.sum("new").over(_upto()).cast("double")).withColumn("fp", F.sum("attached").over(_upto()).cast("double"))
    run = run.join(F.broadcast(whole), F.lit(True))
    f1 = F.try_divide(2 * F.col("tp"), F.col("tp") + F.col("fp") + F.col("c"))
    return run.select(F.col("score").alias("threshold"), F.round(F.try_divide(F.col("tp"), F.col("tp") + F.col("fp")), 6).alias("precision"), F.round(F.try_divide(F.col("tp"), F.col("c").cast("double")), 6).alias("recall"), F.round(F.coalesce(f1, F.lit(0.0)), 6).alias("f1"))


def best_threshold(outcomes: DataFrame) -> DataFrame:
    """(threshold, f1): the best F1; of equal ones the smallest threshold."""
    return f1_curve(outcomes).agg(F.max_by("threshold", F.struct("f1", -F.col("threshold"))).alias("threshold"), F.max("f1").alias("f1"))


def dataset_stats(reports: DataFrame) -> DataFrame:
    """Reports, distinct traces, categories, reports per category, distinct traces per category."""
    per = reports.groupBy("category_id", "fp").agg(F.count("*").alias("n")).groupBy("category_id").agg(F.sum("n").alias("n"), F.count("*").alias("u"))
    by_category = per.agg(F.sum("n").cast("long").alias("n_reports"), F.count("*").alias("n_categories"), F.round(F.avg("n"), 6).alias("avg_reports"), F.round(F.avg("u"), 6).alias("avg_unique"))
    return by_category.join(F.broadcast(reports.agg(F.count_distinct("fp").alias("n_unique"))), F.lit(True)).select("n_reports", "n_unique", "n_categories", "avg_reports", "avg_unique")


def shared_traces(reports: DataFrame) -> DataFrame:
    """(fp, n_categories) of traces that stand in several categories."""
    return reports.groupBy("fp").agg(F.count_distinct("category_id").alias("n_categories")).where("n_categories > 1")


def work_counters(pairs: DataFrame, queries: DataFrame) -> DataFrame:
    """Pair comparisons in all and per query."""
    n = queries.agg(F.count("*").alias("n_queries"))
    return pairs.agg(F.count("*").alias("comparisons")).join(F.broadcast(n), F.lit(True)).select("comparisons", "n_queries", F.round(F.try_divide(F.col("comparisons").cast("double"), F.col("n_queries").cast("double")), 6).alias("per_query"))


def moving_accuracy(outcomes: DataFrame, span: int = 200) -> DataFrame:
    """(query_seq, moving_acc): accuracy over the attached reports of the last `span` arrivals, from bucketed counts.

    A range window over arrivals; buckets of the span keep its partitions bounded, the bucket before is added as an edge.
    """
    old = outcomes.where(~F.col("is_new")).select("query_seq", F.col("correct").cast("double").alias("c")).withColumn("bucket", F.floor(F.col("query_seq") / span))
    # each report also stands in the next bucket, as history only
    both = old.withColumn("own", F.lit(True)).unionByName(old.select("query_seq", "c", (F.col("bucket") + 1).alias("bucket"), F.lit(False).alias("own")))
    w = Window.partitionBy("bucket").orderBy("query_seq").rangeBetween(-(span - 1), 0)
    return both.withColumn("moving_acc", F.round(F.avg("c").over(w), 6)).where("own").select("query_seq", "moving_acc")
