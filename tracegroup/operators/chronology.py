"""Order of arrival, splits by it, and the rules for identical reports."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tracegroup.sources.storage import written

PARTS = (0.7, 0.1, 0.2)


def numbered(reports: DataFrame) -> DataFrame:
    """reports with arrival_seq, 1, 2, … by (arrival, report_id).

    Reports are dealt out by ranges of (arrival, report_id), so that many of one arrival are spread too, and sorted
    within a range, where the place of a row is its rank; to it the number of reports in earlier ranges is added, and
    only those counts meet in one task. Reports are shuffled once. The ranges come from a sample, hence they are written
    once and not drawn again.
    """
    place = F.monotonically_increasing_id()  # partition and row in it
    dealt = written(reports.repartitionByRange("arrival", "report_id").sortWithinPartitions("arrival", "report_id").withColumn("place", place), "arrivals")
    dealt = dealt.withColumn("range", F.shiftright("place", 33))
    sizes = dealt.groupBy("range").agg(F.count("*").alias("n"))
    before = sizes.select("range", F.coalesce(F.sum("n").over(Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    rank = F.col("place").bitwiseAND(F.lit((1 << 33) - 1)) + 1
    return dealt.join(F.broadcast(before), "range").withColumn("arrival_seq", (F.col("before") + rank).cast("long")).drop("range", "place", "before")


def split(reports: DataFrame, parts: tuple[float, float, float] = PARTS) -> DataFrame:
    """reports with part: train, validation or test, by arrival_seq and the number of reports."""
    n = reports.agg(F.count("*").alias("n_reports"))
    train, both = round(parts[0] * 1000), round((parts[0] + parts[1]) * 1000)  # whole numbers, so that no border is rounded
    part = F.when(F.col("arrival_seq") * 1000 <= F.col("n_reports") * train, "train").when(F.col("arrival_seq") * 1000 <= F.col("n_reports") * both, "validation").otherwise("test")
    return reports.join(F.broadcast(n), F.lit(True)).withColumn("part", part).drop("n_reports")


def first_of_trace(reports: DataFrame) -> DataFrame:
    """(fp, first_fp_seq): when each trace arrived first."""
    return reports.groupBy("fp").agg(F.min("arrival_seq").alias("first_fp_seq"))


def drop_identical(reports: DataFrame) -> DataFrame:
    """Reports whose trace has not arrived before."""
    return reports.join(first_of_trace(reports), "fp").where("arrival_seq = first_fp_seq").drop("first_fp_seq")


def identical_shortcut(reports: DataFrame) -> DataFrame:
    """(report_id, category_id) for reports with an identical earlier one: the category of the first report with this trace."""
    first = reports.groupBy("fp").agg(F.min_by("category_id", "arrival_seq").alias("known"), F.min("arrival_seq").alias("first_fp_seq"))
    return reports.join(first, "fp").where("arrival_seq > first_fp_seq").select("report_id", F.col("known").alias("category_id"))


def index_entries(reports: DataFrame) -> DataFrame:
    """(fp, category_id, first_seq): one entry per trace and category, since a trace may stand in several categories."""
    return reports.groupBy("fp", "category_id").agg(F.min("arrival_seq").alias("first_seq"))


def truth(reports: DataFrame) -> DataFrame:
    """reports with is_new: no earlier report has the same category."""
    opened = reports.groupBy("category_id").agg(F.min("arrival_seq").alias("opened_seq"))
    return reports.join(opened, "category_id").withColumn("is_new", F.col("arrival_seq") == F.col("opened_seq")).drop("opened_seq")


def queries_of(reports: DataFrame, part: str = "test", skip_identical: bool = True) -> DataFrame:
    """Reports of a part that are replayed, with is_new. History stays whole: skipped reports count as earlier ones."""
    told = truth(reports)
    if skip_identical:
        told = told.join(first_of_trace(reports), "fp").where("arrival_seq = first_fp_seq").drop("first_fp_seq")
    return told.where(F.col("part") == part)
