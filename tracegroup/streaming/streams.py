"""Reports as a stream: sources, the identical-report shortcut, windows over time, and the method per micro-batch."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tracegroup.functions.frames import fingerprint


def source(spark: SparkSession, path: str, schema: T.StructType | str, form: str = "parquet", files_per_batch: int = 1) -> DataFrame:
    """A folder that files arrive in."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).format(form).load(path)


def timed(stream: DataFrame, column: str = "ts", lateness: str = "1 hour") -> DataFrame:
    """stream with a watermark on `at`. Timestamps without a zone can't carry one, so the column is cast (session zone)."""
    return stream.withColumn("at", F.col(column).cast("timestamp")).withWatermark("at", lateness)


def distinct_traces(reports: DataFrame, lateness: str = "1 hour") -> DataFrame:
    """Reports whose trace did not arrive within the watermark before: what has to be embedded at all. reports: at, frames."""
    return reports.withColumn("fp", fingerprint(F.col("frames"))).withWatermark("at", lateness).dropDuplicatesWithinWatermark(["fp"])


def error_bursts(events: DataFrame, width: str = "24 hours", slide: str = "1 hour") -> DataFrame:
    """(w, n_errors) per sliding window."""
    return events.where("event_type = 'error'").groupBy(F.window("at", width, slide).alias("w")).agg(F.count("*").alias("n_errors"))


def user_sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """(user_id, w, n_events, n_errors) per session."""
    return events.groupBy("user_id", F.session_window("at", gap).alias("w")).agg(F.count("*").alias("n_events"), F.count(F.when(F.col("event_type") == "error", 1)).alias("n_errors"))


def errors_after_clicks(events: DataFrame, within: str = "10 minutes") -> DataFrame:
    """Errors with the clicks and views of the same user in the time before: an interval join of the stream with itself."""
    e = events.where("event_type = 'error'").select(F.col("user_id"), F.col("event_id").alias("error_id"), F.col("at").alias("error_at"))
    c = events.where("event_type in ('click', 'view')").select(F.col("user_id").alias("who"), F.col("event_id").alias("cause_id"), F.col("at").alias("cause_at"))
    return e.join(c, F.expr(f"user_id = who and cause_at <= error_at and cause_at >= error_at - interval {within}")).select("user_id", "error_id", "cause_id", "error_at", "cause_at")


COUNTERS = T.StructType([T.StructField("category_id", T.StringType()), T.StructField("n_reports", T.LongType()), T.StructField("first_us", T.LongType()), T.StructField("last_us", T.LongType())])


def category_counters(assigned: DataFrame) -> DataFrame:
    """(category_id, n_reports, first_us, last_us) so far, updated with every batch. assigned: category_id, arrival_us."""

    def count(key: tuple, frames: Iterator[pd.DataFrame], state: Any) -> Iterator[pd.DataFrame]:
        n, first, last = state.get if state.exists else (0, None, None)
        for f in frames:
            n += len(f)
            low, high = int(f["arrival_us"].min()), int(f["arrival_us"].max())
            first, last = low if first is None else min(first, low), high if last is None else max(last, high)
        state.update((n, first, last))
        yield pd.DataFrame({"category_id": [key[0]], "n_reports": [n], "first_us": [first], "last_us": [last]})

    state = T.StructType([T.StructField("n", T.LongType()), T.StructField("first", T.LongType()), T.StructField("last", T.LongType())])
    return assigned.groupBy("category_id").applyInPandasWithState(count, COUNTERS, state, "update", "NoTimeout")


def per_batch(stream: DataFrame, handle: Callable[[DataFrame, int], None], checkpoint: str, once: bool = True):
    """Start the stream and hand each micro-batch with its number to `handle`, which should write by that number so that a repeat changes nothing."""
    writer = stream.writeStream.foreachBatch(handle).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if once else writer).start()


def attach_batch(history: DataFrame, batch: DataFrame, scorer, threshold: float) -> DataFrame:
    """Decisions for a batch of reports (arrival_seq, fp, frames) against history (arrival_seq, fp, frames, category_id) and earlier reports of the batch.

    As each report is also held against those before it in the batch, and chains of attachments are followed to
    their root, decisions do not depend on where batches begin.
    """
    from tracegroup.operators import baselines, replay
    from tracegroup.operators.decide import assign

    new = batch.select("arrival_seq", "fp", "frames", F.concat(F.lit("new:"), F.col("arrival_seq").cast("string")).alias("category_id"))
    every = history.select("arrival_seq", "fp", "frames", "category_id").unionByName(new)
    queries = new.withColumn("is_new", F.lit(True))
    scored = scorer(baselines.traces_of(queries), baselines.traces_of(every))
    entries = every.groupBy("fp", "category_id").agg(F.min("arrival_seq").alias("first_seq"))
    found = replay.outcomes(queries, replay.ranked(replay.category_scores(replay.earlier_pairs(queries, scored, entries))))
    told = found.withColumn("action", F.when(F.col("score") > threshold, "attach").otherwise("create"))
    return assign(told, history)
