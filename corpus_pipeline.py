"""A corpus pipeline: quality, exact copies, near copies, mixing, packing, each stage over all that the one before kept.

Every stage takes rows with null or repeated ids, null, empty and very long texts, null languages and sources, and
columns of any further name, which pass through up to the last stage. Empty tables give empty results.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tracegroup.llm import exact_dedup, mixing, ngram_join, packing, quality
from tracegroup.llm.common import shared_dir
from tracegroup.llm.queries import domain, quality_weights

#: Parts of the mix: nine tenths of the tokens that are left, no document twice.
MIX = mixing.MixConfig(share_of_all=900, most_epochs=1)


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """docs that the quality classifier accepts. It is trained on the labelled rows of docs that are not held out.

    Equal texts are judged alike; null and empty texts by the bias alone. Without any label all score 0.5, so none is accepted.
    """
    weights = quality_weights(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    scored = quality.score(docs, weights, out="quality score")
    return scored.where(F.col("quality score") >= 0.7).drop("quality score")


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of equal texts (A-Z lower-cased, null as empty): that of the largest doc_id, a null one being smallest."""
    return exact_dedup.drop_exact(docs)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near copies: that of the smallest doc_id, a null one being largest. Texts without words have no copies but rows equal in id and text."""
    return ngram_join.keep_one(docs)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """docs without those that the leaves' budgets have no room for. A null language or source is a leaf of its own; rows of equal id in a leaf go or stay together."""
    return mixing.mixed(docs, domain(), MIX)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Where each piece of each row's document lies in the sequences of 2048 tokens. A null or empty text is one piece, its end mark."""
    return packing.pack(docs)


STAGES = [
    ("quality classifier", quality_stage),
    ("exact dedup", exact_stage),
    ("n-gram Jaccard join", near_stage),
    ("mixing sources to target weights", mixing_stage),
    ("best-fit packing", packing_stage),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; what each returns is written as Parquet and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        if k == len(STAGES) - 1:
            return out
        path = f"{shared_dir(spark)}/stage-{k}-{uuid.uuid4().hex}"
        out.write.parquet(path)
        docs = spark.read.parquet(path)
    return docs


#: Training, tokenisation and packing have no SQL twin; tests hold the stages against brute force.
ORACLE_SQL = None
