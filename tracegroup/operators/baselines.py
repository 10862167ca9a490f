"""Comparison methods that need no training of a network, over distinct traces that share a frame.

Each scorer takes traces (fp, frames, is_query, is_base) and returns pairs (q_fp, c_fp, score) with score
above 0. Pairs that share nothing score 0 and are left out; a query without pairs scores 0.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tracegroup.functions.frames import concatenated

Scorer = Callable[[DataFrame, DataFrame], DataFrame]


def traces_of(reports: DataFrame) -> DataFrame:
    """(fp, frames) of the distinct traces."""
    return reports.groupBy("fp").agg(F.first("frames").alias("frames"))


def document_frequencies(training: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(frame, df) over training reports, and their number as one row."""
    df = training.select(F.explode(F.array_distinct("frames")).alias("frame")).groupBy("frame").agg(F.count("*").alias("df"))
    return df, training.agg(F.count("*").alias("n_training"))


def postings(traces: DataFrame) -> DataFrame:
    """(fp, frame, pos, nth, n, tf): every occurrence, with its place from the top, its number among equal frames, and counts."""
    rows = traces.select("fp", F.size("frames").alias("n"), "frames", F.posexplode("frames").alias("pos", "frame"))
    nth = F.size(F.filter(F.slice("frames", 1, F.col("pos") + 1), lambda x: x == F.col("frame")))
    tf = F.size(F.filter("frames", lambda x: x == F.col("frame")))
    return rows.select("fp", "frame", (F.col("pos") + 1).alias("pos"), nth.alias("nth"), "n", tf.alias("tf"))


def _met(left: DataFrame, right: DataFrame, on: list[str]) -> DataFrame:
    """Pairs of different roles at equal keys; columns of the left side begin with q_, of the right with c_."""
    q = left.select(*on, *[F.col(c).alias(f"q_{c}") for c in left.columns if c not in on])
    c = right.select(*on, *[F.col(c).alias(f"c_{c}") for c in right.columns if c not in on])
    return q.join(c, on)


def set_overlap(queries: DataFrame, base: DataFrame) -> DataFrame:
    """Shared distinct frames over all distinct frames."""
    flat = lambda t: t.select("fp", F.size(F.array_distinct("frames")).alias("n"), F.explode(F.array_distinct("frames")).alias("frame"))
    both = _met(flat(queries), flat(base), ["frame"]).groupBy("q_fp", "c_fp").agg(F.count("*").alias("i"), F.first("q_n").alias("a"), F.first("c_n").alias("b"))
    return both.select("q_fp", "c_fp", (F.col("i") / (F.col("a") + F.col("b") - F.col("i"))).alias("score"))


@dataclass(frozen=True)
class TfIdf:
    """dampened: sum over shared frames of sqrt(tf in the candidate) * idf² / sqrt(frames of the candidate); cosine: of tf * idf vectors.

    idf = 1 + ln(N / (df + 1)) over training reports; frames never seen there have df 0.
    """

    training: DataFrame
    mode: str = "dampened"

    def __call__(self, queries: DataFrame, base: DataFrame) -> DataFrame:
        df, n = document_frequencies(self.training)
        idf = F.lit(1.0) + F.log(F.col("n_training") / (F.coalesce("df", F.lit(0)) + 1))

        def weighted(traces: DataFrame) -> DataFrame:
            flat = traces.select("fp", F.size("frames").alias("n"), F.explode("frames").alias("frame")).groupBy("fp", "frame").agg(F.count("*").alias("tf"), F.first("n").alias("n"))
            return flat.join(df, "frame", "left").join(F.broadcast(n), F.lit(True)).select("fp", "frame", "tf", "n", idf.alias("idf"))

        q, c = weighted(queries), weighted(base)
        met = _met(q, c, ["frame"])
        if self.mode == "dampened":
            part = F.sqrt("c_tf") * F.col("c_idf") * F.col("c_idf") / F.sqrt("c_n")
            return met.groupBy("q_fp", "c_fp").agg(F.sum(part).alias("score"))
        norm = lambda t, name: t.groupBy("fp").agg(F.sqrt(F.sum(F.pow(F.col("tf") * F.col("idf"), 2))).alias("l")).toDF(f"{name}_fp", f"{name}_l")
        dot = met.groupBy("q_fp", "c_fp").agg(F.sum(F.col("q_tf") * F.col("q_idf") * F.col("c_tf") * F.col("c_idf")).alias("dot"))
        return dot.join(norm(q, "q"), "q_fp").join(norm(c, "c"), "c_fp").select("q_fp", "c_fp", (F.col("dot") / (F.col("q_l") * F.col("c_l"))).alias("score"))


@dataclass(frozen=True)
class TopFrameAlign:
    """Linear alignment that favours frames near the top and rare ones.

    The r-th occurrence of a frame meets the other trace's r-th; a place i weighs i^-alpha * exp(-beta * df / N);
    a meeting counts both weights, damped by exp(-gamma * distance of places), over all weights of both traces.
    """

    training: DataFrame
    alpha: float = 1.0
    beta: float = 2.0
    gamma: float = 0.1

    def __call__(self, queries: DataFrame, base: DataFrame) -> DataFrame:
        df, n = document_frequencies(self.training)
        weight = F.pow(F.col("pos").cast("double"), F.lit(-self.alpha)) * F.exp(F.lit(-self.beta) * F.coalesce("df", F.lit(0)) / F.col("n_training"))

        def weighted(traces: DataFrame) -> DataFrame:
            return postings(traces).join(df, "frame", "left").join(F.broadcast(n), F.lit(True)).select("fp", "frame", "nth", "pos", weight.alias("w"))

        q, c = weighted(queries), weighted(base)
        part = (F.col("q_w") + F.col("c_w")) * F.exp(F.lit(-self.gamma) * F.abs(F.col("q_pos") - F.col("c_pos")))
        met = _met(q, c, ["frame", "nth"]).groupBy("q_fp", "c_fp").agg(F.sum(part).alias("m"))
        total = lambda t, name: t.groupBy("fp").agg(F.sum("w").alias("t")).toDF(f"{name}_fp", f"{name}_t")
        return met.join(total(q, "q"), "q_fp").join(total(c, "c"), "c_fp").select("q_fp", "c_fp", (F.col("m") / (F.col("q_t") + F.col("c_t"))).alias("score"))


def common_prefix(a: Column, b: Column) -> Column:
    """Number of frames that two traces share from the top."""
    off = F.array_position(F.zip_with(a, b, lambda x, y: x.eqNullSafe(y)), False)
    return F.when(off > 0, off - 1).otherwise(F.size(a).cast("long"))


def prefix_match(queries: DataFrame, base: DataFrame) -> DataFrame:
    """Common prefix over the longer trace's length. Traces meet by their top frame."""
    head = lambda t: t.where("size(frames) > 0").select(F.col("frames")[0].alias("head"), "fp", "frames")
    met = _met(head(queries), head(base), ["head"])
    return met.select("q_fp", "c_fp", (common_prefix(F.col("q_frames"), F.col("c_frames")) / F.greatest(F.size("q_frames"), F.size("c_frames"))).alias("score"))


def frame_edit_distance(a: list, b: list) -> int:
    """Insertions, deletions and replacements of frames between two traces, a row of the table at a time."""
    ids = {f: i for i, f in enumerate(dict.fromkeys([*a, *b]))}
    x, y = np.array([ids[f] for f in a]), np.array([ids[f] for f in b])
    row = np.arange(len(y) + 1)
    for i, f in enumerate(x, 1):
        best = np.minimum(row[1:] + 1, row[:-1] + (y != f))
        # insertions run along the row: a running minimum of what is left after taking the place away
        run = np.concatenate([[i], best]) - np.arange(len(y) + 1)
        row = np.minimum.accumulate(run) + np.arange(len(y) + 1)
    return int(row[-1])


@dataclass(frozen=True)
class EditDistance:
    """1 - distance / longer length, over characters of the concatenated frames or over frames; pairs that share a frame."""

    unit: str = "frame"

    def __call__(self, queries: DataFrame, base: DataFrame) -> DataFrame:
        pairs = set_overlap(queries, base).select("q_fp", "c_fp")
        text = lambda t, n: t.toDF(f"{n}_fp", f"{n}_frames")
        met = pairs.join(text(queries.select("fp", "frames"), "q"), "q_fp").join(text(base.select("fp", "frames"), "c"), "c_fp")
        if self.unit == "char":
            a, b = concatenated(F.col("q_frames")), concatenated(F.col("c_frames"))
            return met.select("q_fp", "c_fp", (1 - F.levenshtein(a, b) / F.greatest(F.length(a), F.length(b), F.lit(1))).alias("score"))

        @F.pandas_udf("double")
        def similarity(q: pd.Series, c: pd.Series) -> pd.Series:
            return pd.Series([1 - frame_edit_distance(list(a), list(b)) / max(len(a), len(b), 1) for a, b in zip(q, c, strict=True)])

        return met.select("q_fp", "c_fp", similarity("q_frames", "c_frames").alias("score"))


def hashed_ngrams(texts: list[str], size: int = 512, orders: tuple[int, ...] = (3, 4)) -> np.ndarray:
    """A stand-in for a hosted text-embedding model: signed hashed character n-grams, square roots of counts, unit length."""
    import xxhash

    out = np.zeros((len(texts), size))
    for row, text in enumerate(texts):
        for n in orders:
            for i in range(len(text) - n + 1):
                h = xxhash.xxh64_intdigest(text[i : i + n].encode())
                out[row, h % size] += 1 if h >> 63 else -1
    out = np.sign(out) * np.sqrt(np.abs(out))
    norm = np.linalg.norm(out, axis=1, keepdims=True)
    return (out / np.where(norm > 0, norm, 1)).astype(np.float32)


def text_vectors(traces: DataFrame, embed: Callable[[list[str]], np.ndarray] = hashed_ngrams, delimiter: str = "\n", most_frames: int | None = None) -> DataFrame:
    """(fp, vec) of traces' concatenated frames by a text-embedding function; a hosted model would be called from here, a batch at a time."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            vectors = embed(batch.column("text").to_pylist()) if batch.num_rows else np.zeros((0, 1), np.float32)
            yield pa.RecordBatch.from_arrays([batch.column("fp"), pa.array(list(vectors), pa.list_(pa.float32()))], ["fp", "vec"])

    return traces.select("fp", concatenated(F.col("frames"), delimiter, most_frames).alias("text")).mapInArrow(run, "fp string, vec array<float>")
