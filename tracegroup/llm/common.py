"""Shared pieces: bounded membership masks, batch slicing; tables in the shared folder and components come from the engine."""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tracegroup.operators.components import components
from tracegroup.sources.storage import shared_dir, written

__all__ = ["components", "shared_dir", "written"]

#: glibc's names of the size from which memory is mapped by itself, and of the number of arenas.
_MAPPED_FROM, _ARENAS = -3, -8


def _give_back() -> None:
    """Let this process return the memory of large arrays when they are freed, as idle Python workers otherwise keep their peak."""
    pa.set_memory_pool(pa.system_memory_pool())
    try:
        libc = ctypes.CDLL("libc.so.6")
        libc.mallopt(_MAPPED_FROM, 1 << 20)
        libc.mallopt(_ARENAS, 1)
    except (OSError, AttributeError):
        pass  # another C library: workers are larger, results the same


_give_back()

#: A membership mask has 2**MASK_BITS bits, so at most 2**(MASK_BITS - 6) rows of one word each.
MASK_BITS = 24
#: Text bytes that a kernel works on at a time (a longer text is taken alone).
SLICE_BYTES = 2 << 20
#: Bytes of a record batch.
BATCH_BYTES = 4 << 20


def small_batches(df: DataFrame) -> DataFrame:
    """df, after a runtime setting that keeps the record batches that Python is given to a few MB; a longer row is a batch of its own."""
    df.sparkSession.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))
    return df


def mask_of(df: DataFrame, hashed: Column) -> DataFrame:
    """The bits that the values of `hashed` set, as rows of words: at most 2**(MASK_BITS-6) rows however large df is."""
    bit = F.pmod(hashed, F.lit(1 << MASK_BITS))
    at = df.select(F.shiftright(bit, 6).alias("mask at"), (bit % 64).cast("int").alias("bit"))
    return at.groupBy("mask at").agg(F.bit_or(F.expr("shiftleft(1L, bit)")).alias("mask word"))


def masked(df: DataFrame, hashed: Column, mask: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Rows of df that may be in the mask, and those that surely are not. The broadcast is bounded by the mask's size; columns of any name pass."""
    bit = F.pmod(hashed, F.lit(1 << MASK_BITS))
    rows = df.select(F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("given"), F.shiftright(bit, 6).alias("mask at"), (bit % 64).cast("int").alias("mask bit"))
    found = rows.join(F.broadcast(mask), "mask at", "left").withColumn("hit", F.coalesce(F.expr("(shiftright(`mask word`, `mask bit`) & 1L) = 1L"), F.lit(False)))
    return found.where("hit").select("given.*"), found.where("not hit").select("given.*")


def bytes_of(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string or binary column, one after another, and where each row's begin (one more than rows). Null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if not pa.types.is_large_binary(column.type):
        column = column.cast(pa.large_binary())
    if column.null_count:
        column = column.fill_null(b"")
    offsets = np.frombuffer(column.buffers()[1], np.int64, len(column) + 1, column.offset * 8)
    buffer = column.buffers()[2]
    data = np.frombuffer(buffer, np.uint8) if buffer is not None else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def slices(offsets: np.ndarray, most: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges whose texts together have at most `most` bytes; a longer text is a range of its own."""
    n, at = len(offsets) - 1, 0
    while at < n:
        end = int(np.searchsorted(offsets, offsets[at] + most, "right")) - 1
        end = min(n, max(end, at + 1))
        yield at, end
        at = end


def batches(**columns) -> Iterator[pa.RecordBatch]:
    """One record batch, if it has rows."""
    batch = pa.RecordBatch.from_pydict(columns)
    if batch.num_rows:
        yield batch
