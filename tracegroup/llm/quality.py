"""Quality classifier: hashed word n-grams, logistic regression by follow-the-regularised-leader, sparse dot products."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructType

from tracegroup.llm import bytehash
from tracegroup.llm.common import batches, bytes_of, slices, small_batches


@dataclass(frozen=True)
class QualityConfig:
    """sample_rows bounds the labelled rows that the fit reads; everything else covers all rows."""

    bits: int = 18
    sample_rows: int = 16_000
    epochs: int = 3
    alpha: float = 0.6
    beta: float = 1.0
    l1: float = 0.0
    l2: float = 1e-4
    gain: float = 12.0
    seed: int = 7


#: Token classes of bytes: 0 white space, 1 letters, digits and all beyond ASCII, 2 other signs.
_CLASS = np.where(bytehash.WORD, 2, 0).astype(np.uint8)
_CLASS[48:58] = _CLASS[65:91] = _CLASS[97:123] = _CLASS[128:] = 1
_REPEAT = np.uint64(0x5851F42D4C957F2D)
_PAIR = np.uint64(0xDA942042E4DD58B5)


def features(data: np.ndarray, offsets: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Feature number and row of every word and word pair. A word equal to the one before it is read as a repeat mark."""
    start, end, row = bytehash.spans(data, offsets, _CLASS)
    h = bytehash.token_hashes(bytehash.LOWER[data], start, end)
    same = row[1:] == row[:-1]
    again = np.flatnonzero(same & (h[1:] == h[:-1])) + 1
    h[again] = _REPEAT
    pairs = bytehash.mix(h[:-1] * _PAIR + h[1:])[same]
    shift = np.uint64(64 - bits)
    return np.concatenate([h >> shift, pairs >> shift]).astype(np.int64), np.concatenate([row, row[1:][same]])


def fit(rows: Iterator[tuple[int, np.ndarray]], config: QualityConfig) -> np.ndarray:
    """Weights (the last is the bias) from (label, feature numbers of one text), by proximal follow-the-regularised-leader."""
    size = 1 << config.bits
    z, n, w = (np.zeros(size + 1) for _ in range(3))
    examples = []
    for label, at in rows:
        used, count = np.unique(at, return_counts=True)
        examples.append((label, len(at), used.astype(np.int32), count.astype(np.int32)))
    order = np.random.default_rng(config.seed)
    for _ in range(config.epochs):
        for i in order.permutation(len(examples)):
            label, total, used, count = examples[i]
            at, x = np.append(used, size), np.append(config.gain * count / max(1, total), 1.0)
            zi, ni = z[at], n[at]
            wi = np.where(np.abs(zi) <= config.l1, 0.0, -(zi - np.sign(zi) * config.l1) / ((config.beta + np.sqrt(ni)) / config.alpha + config.l2))
            p = 1 / (1 + np.exp(-np.clip(wi @ x, -35, 35)))
            g = (p - label) * x
            step = (np.sqrt(ni + g * g) - np.sqrt(ni)) / config.alpha
            z[at], n[at] = zi + g - step * wi, ni + g * g
    w = np.where(np.abs(z) <= config.l1, 0.0, -(z - np.sign(z) * config.l1) / ((config.beta + np.sqrt(n)) / config.alpha + config.l2))
    return w.astype(np.float32)


def train(docs: DataFrame, labels: DataFrame, config: QualityConfig = QualityConfig(), label: str = "quality") -> np.ndarray:
    """Fit on a sample of labelled rows, the first `sample_rows` in hash order.

    labels: doc_id and a label of 0 or 1; other labels, null ids and rows without a text row are not learned from.
    The sample is bounded, so it is broadcast to the texts and gathered in one task, which fits the weights.
    Without any labelled row all weights are 0, and every text scores 0.5.
    """
    rows = labels.where(F.col(label).isin(0, 1) & F.col("doc_id").isNotNull()).select("doc_id", F.col(label).cast("int").alias("label"))
    picked = rows.distinct().orderBy(F.xxhash64("doc_id"), "doc_id", "label").limit(config.sample_rows)
    texts = small_batches(docs).select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(picked), "doc_id")

    def featurise(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            data, offsets = bytes_of(batch.column("text"))
            for a, b in slices(offsets):
                at, row = features(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], config.bits)
                at = at[np.argsort(row, kind="stable")].astype(np.int32)
                cut = np.concatenate([[0], np.cumsum(np.bincount(row, minlength=b - a))])
                part = batch.slice(a, b - a)
                yield from batches(doc_id=part.column("doc_id"), label=part.column("label"), at=pa.ListArray.from_arrays(pa.array(cut, pa.int32()), pa.array(at)))

    def learn(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = ((int(y), at) for batch in it for y, at in zip(batch.column("label").to_numpy(), batch.column("at").to_numpy(zero_copy_only=False), strict=True))
        yield from batches(weights=[fit(rows, config).tobytes()])

    found = texts.mapInArrow(featurise, "doc_id long, label int, at array<int>").repartition(1).sortWithinPartitions(F.xxhash64("doc_id"), "doc_id", "label", F.hash("at"))
    got = found.mapInArrow(learn, "weights binary").collect()
    return np.frombuffer(got[0][0], np.float32) if got else np.zeros((1 << config.bits) + 1, np.float32)


def score(docs: DataFrame, weights: np.ndarray, config: QualityConfig = QualityConfig(), text: str = "text", out: str = "score") -> DataFrame:
    """docs with a column `out` from 0 to 1, from the whole text alone. Null and empty texts score the bias."""
    shared = small_batches(docs).sparkSession.sparkContext.broadcast(weights)
    keep = [c for c in docs.columns if c != out]

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w = shared.value
        for batch in it:
            data, offsets = bytes_of(batch.column(batch.schema.get_field_index("scored text")))
            total = np.zeros(batch.num_rows)
            for a, b in slices(offsets):
                at, row = features(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], config.bits)
                n = np.bincount(row, minlength=b - a)
                total[a:b] = config.gain * np.bincount(row, w[at], minlength=b - a) / np.maximum(n, 1)
            p = 1 / (1 + np.exp(-np.clip(total + w[-1], -35, 35)))
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(p)], [*keep, out])

    kind = StructType([*docs.select(*[F.col(f"`{c}`") for c in keep]).schema.fields]).add(out, DoubleType())
    return docs.select(*[F.col(f"`{c}`") for c in keep], F.col(f"`{text}`").alias("scored text")).mapInArrow(run, kind)
