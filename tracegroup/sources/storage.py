"""Reading the given tables and crash dumps, writing results, and tables in the folder that executors share."""

from __future__ import annotations

import uuid
from collections.abc import Iterable, Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

REPORT = T.StructType(
    [
        T.StructField("report_id", T.LongType()),
        T.StructField("arrival", T.LongType()),
        T.StructField("frames", T.ArrayType(T.StringType())),
        T.StructField("category_id", T.StringType()),
        T.StructField("meta", T.MapType(T.StringType(), T.StringType())),
    ]
)


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir; where it is unset, one of our own if the driver is the only machine, else an error."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        current = spark.sparkContext._jsc.sc().getCheckpointDir()
        found = current.get() if current.isDefined() else None
    if not found:
        if not on_one_machine(spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share: tables on their own disks would be lost to each other")
        found = "/tmp/tracegroup-checkpoints"
    return found.rstrip("/")


def on_one_machine(master: str) -> bool:
    """Whether driver and executors are one process: local, local[n], local[*]; not local-cluster[...], whose folders are apart."""
    return master == "local" or master.startswith("local[")


#: Spark's setting by which the shuffle files of a plan are removed when it has run.
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextmanager
def freed(spark: SparkSession) -> Iterator[None]:
    """Shuffle files of plans that run in here go when a plan has run; elsewhere they stay until the driver happens to collect its garbage."""
    before = spark.conf.get(_CLEANUP, "false")
    spark.conf.set(_CLEANUP, "true")
    try:
        yield
    finally:
        spark.conf.set(_CLEANUP, before)


def written(df: DataFrame, what: str) -> DataFrame:
    """Write df as Parquet below the shared folder and read it back: lineage ends there, and a lost executor costs nothing."""
    return written_in_turn([df], what)


def written_in_turn(portions: Iterable[DataFrame], what: str) -> DataFrame:
    """Portions of a table, one or more, as one such table. A portion's shuffle files are gone before the next one is made."""
    path = None
    for df in portions:
        spark, schema = df.sparkSession, df.schema
        path = path or f"{shared_dir(spark)}/{what}-{uuid.uuid4().hex}"
        with freed(spark):
            df.write.mode("append").option("compression", "zstd").parquet(path)
    return spark.read.schema(schema).parquet(path)


def read_json_reports(spark: SparkSession, path: str) -> DataFrame:
    """Reports as JSON lines of the REPORT schema. Lines that don't parse come back in `corrupt`, the other fields null."""
    schema = T.StructType([*REPORT.fields, T.StructField("corrupt", T.StringType())])
    return spark.read.schema(schema).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "corrupt").json(path)


def read_csv_reports(spark: SparkSession, path: str, delimiter: str = ";") -> DataFrame:
    """Reports as CSV with the columns report_id, arrival, category_id and frames, the frames joined by `delimiter`."""
    schema = "report_id long, arrival long, category_id string, frames string"
    return spark.read.schema(schema).option("header", True).csv(path).withColumn("frames", F.split("frames", delimiter))


def read_text_traces(spark: SparkSession, path: str, frames: Column | None = None) -> DataFrame:
    """One file, one printed trace: (path, text, frames), the frames taken from lines as functions.frames.from_text does."""
    from tracegroup.functions.frames import from_text

    found = spark.read.option("wholetext", True).text(path).select(F.input_file_name().alias("path"), F.col("value").alias("text"))
    return found.withColumn("frames", from_text(F.col("text")) if frames is None else frames)


def save_partitioned(df: DataFrame, path: str, *by: str) -> None:
    """Decisions by day, vectors by cell: a Parquet table in folders, so that later scans read only what they ask for."""
    df.write.mode("overwrite").partitionBy(*by).parquet(path)


def run_only(df: DataFrame) -> None:
    """Run a plan and throw its rows away, for timing."""
    df.write.format("noop").mode("overwrite").save()
