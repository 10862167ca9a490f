"""Joins by time that have no built-in operator: pairs within a band, and the latest row before."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def range_join(left: DataFrame, right: DataFrame, left_at: str, right_at: str, width: int) -> DataFrame:
    """Pairs of rows with 0 <= right_at - left_at < width, columns of both sides.

    Time is cut into buckets of `width`; a right row can only be met from its own bucket and the one before, so both
    sides meet by an equi-join on the bucket, which AQE splits where many rows fall into one. Null times meet nothing.
    """
    bucket = "bucket of the band"
    a = left.withColumn(bucket, F.explode(F.array(F.floor(F.col(left_at) / width), F.floor(F.col(left_at) / width) + 1)))
    b = right.withColumn(bucket, F.floor(F.col(right_at) / width))
    gap = F.col(right_at) - F.col(left_at)
    return a.join(b, bucket).where((gap >= 0) & (gap < width)).drop(bucket)


def as_of_join(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """left with `value` and `since` of the right row of its key with the largest time not after its own; null if there is none.

    Both sides go into one sort per key, and the last right row seen is carried on, so no pairs are made. Of right rows at one time the largest value counts.
    """
    names = left.columns
    rows = left.select(F.col(key).alias("k"), F.col(at).alias("t"), F.lit(1).alias("side"), F.struct(*names).alias("own"), F.lit(None).cast(right.schema[value].dataType).alias("v"))
    seen = right.groupBy(F.col(key).alias("k"), F.col(at).alias("t")).agg(F.max(value).alias("v"))
    both = rows.unionByName(seen.select("k", "t", F.lit(0).alias("side"), F.lit(None).cast(rows.schema["own"].dataType).alias("own"), "v"))
    upto = Window.partitionBy("k").orderBy("t", "side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    carried = F.last(F.when(F.col("side") == 0, F.struct(F.col("v").alias("v"), F.col("t").alias("t"))), ignorenulls=True).over(upto)
    met = both.withColumn("met", carried).where("side = 1")
    return met.select("own.*", F.col("met.v").alias(value), F.col("met.t").alias("since"))
