"""The engine's functions for SQL users."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


class FramesOfText:
    """Table function: a printed trace as rows (pos, package, class_name, method)."""

    def eval(self, text: str) -> Iterator[tuple]:
        import re

        at = 0
        for line in (text or "").splitlines():
            m = re.match(r"\s*(?:at\s+|#\d+\s+(?:0x[0-9a-fA-F]+\s+in\s+)?)([^\s(]+)", line)
            if m:
                parts = m[1].split(".")
                yield at, ".".join(parts[:-2]), parts[-2] if len(parts) > 1 else "", parts[-1]
                at += 1


def _mean(v: pd.Series) -> list:
    return np.stack(v.to_list()).mean(0).tolist()


def _max(v: pd.Series) -> list:
    return np.stack(v.to_list()).max(0).tolist()


def register(spark: SparkSession) -> None:
    """frames_of_text(text) as a table function; vec_mean(vec) and vec_max(vec) as aggregates; frame_similarity(a, b) over frame arrays."""
    from tracegroup.operators.baselines import frame_edit_distance

    spark.udtf.register("frames_of_text", F.udtf(FramesOfText, returnType="pos int, package string, class_name string, method string"))

    @F.pandas_udf("array<double>")
    def vec_mean(v: pd.Series) -> list:
        return _mean(v)

    @F.pandas_udf("array<double>")
    def vec_max(v: pd.Series) -> list:
        return _max(v)

    @F.pandas_udf("double")
    def frame_similarity(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([1 - frame_edit_distance(list(x), list(y)) / max(len(x), len(y), 1) for x, y in zip(a, b, strict=True)])

    for f in (vec_mean, vec_max, frame_similarity):
        spark.udf.register(f.__name__, f)


def views(tables: dict[str, DataFrame]) -> None:
    """Name DataFrames for SQL."""
    for name, df in tables.items():
        df.createOrReplaceTempView(name)
