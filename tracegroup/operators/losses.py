"""Training losses, on arrays with gradients and on DataFrames."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tracegroup.operators.nn import sigmoid, softplus


def info_nce(s: np.ndarray, tau: float = 0.1, denominator: str = "negatives", same: np.ndarray | None = None) -> tuple[float, np.ndarray]:
    """Contrastive loss of a square similarity matrix, positives on the diagonal, and its gradient.

    Each anchor's loss is minus its positive plus the log of the summed exponentials of its negatives; with
    denominator="all" of the positive too. same[i, k] marks negatives to leave out because they share the
    anchor's category; an anchor without negatives does not count.
    """
    x = s / tau
    n = len(x)
    eye = np.eye(n, dtype=bool)
    use = ~eye if denominator == "negatives" else np.ones_like(eye)
    if same is not None:
        use = use & (~same | eye)
    counts = (use & ~eye).any(1)
    shut = np.where(use, x, -np.inf)
    top = np.where(counts, shut.max(1, initial=-np.inf, where=use), 0.0)
    e = np.where(use, np.exp(np.where(use, x, 0) - top[:, None]), 0)
    z = np.maximum(e.sum(1), 1e-300)
    m = max(int(counts.sum()), 1)
    each = np.where(counts, -np.diag(x) + top + np.log(z), 0)
    grad = np.where(counts[:, None], e / z[:, None] - eye, 0) / (m * tau)
    return float(each.sum() / m), grad


def bce_pair(positive: np.ndarray, negative: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
    """Logistic loss that asks for a high score of the positive pair and a low one of the negative, and its gradients."""
    n = max(len(positive), 1)
    return float((softplus(-positive) + softplus(negative)).sum() / n), -sigmoid(-positive) / n, sigmoid(negative) / n


def softplus_column(x: Column) -> Column:
    return F.greatest(x, F.lit(0.0)) + F.log1p(F.exp(-F.abs(x)))


def info_nce_table(pairs: DataFrame, tau: float = 0.1, denominator: str = "negatives") -> DataFrame:
    """(anchor, loss) from (anchor, other, is_positive, similarity), shifted by the greatest term."""
    x = F.col("similarity") / tau
    used = x if denominator == "all" else F.when(~F.col("is_positive"), x)
    t = pairs.select("anchor", "is_positive", x.alias("x"), used.alias("u"))
    top = t.groupBy("anchor").agg(F.max("u").alias("m"), F.max(F.when(F.col("is_positive"), F.col("x"))).alias("p"))
    summed = t.join(top, "anchor").groupBy("anchor", "m", "p").agg(F.sum(F.exp(F.col("u") - F.col("m"))).alias("z"))
    return summed.where("z is not null").select("anchor", F.round(-F.col("p") + F.col("m") + F.log("z"), 6).alias("loss"))


def bce_table(triplets: DataFrame) -> DataFrame:
    """triplets (…, positive_score, negative_score) with their loss."""
    return triplets.withColumn("loss", F.round(softplus_column(-F.col("positive_score")) + softplus_column(F.col("negative_score")), 6))
