"""Exact dedup by polynomial fingerprints that compose, with a chunkwise comparison of texts whose fingerprints agree.

A text's fingerprint is the sum of byte * BASE**position modulo the prime 2**61 - 1. Chunks are hashed
on their own and combined by shifting: fp(xy) = fp(x) + BASE**len(x) * fp(y). Texts of over
`parallel_bytes` bytes are cut into chunks that other tasks hash.
"""

from __future__ import annotations

import hashlib
from collections import OrderedDict
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType, LongType, StringType, StructType

from tracegroup.llm.common import mask_of, masked, small_batches, written

PRIME = (1 << 61) - 1
BASE = 0x1F3B5C7D9E8A6421 % PRIME
CHUNK = 1 << 16
#: Texts that a task keeps at hand to find repeats before anything is shuffled.
LOCAL_BYTES = 8 << 20


@lru_cache(maxsize=4)
def _limbs(base: int, prime: int) -> tuple[np.ndarray, np.ndarray]:
    """BASE**i for a chunk's positions, as words below and above bit 31."""
    up, x = [], 1
    for _ in range(CHUNK):
        up.append(x)
        x = x * base % prime
    word = np.array(up, np.uint64)
    return (word & np.uint64((1 << 31) - 1)).astype(np.int64), (word >> np.uint64(31)).astype(np.int64)


def chunk_hash(chunk: bytes, base: int = BASE, prime: int = PRIME) -> int:
    """Hash of at most CHUNK bytes. Each limb's dot product stays below 2**55, so it is exact."""
    low, high = _limbs(base, prime)
    b = np.frombuffer(chunk, np.uint8).astype(np.int64)
    return (int(b @ low[: len(b)]) + (int(b @ high[: len(b)]) << 31)) % prime


def combine(parts: Iterator[tuple[int, int]], base: int = BASE, prime: int = PRIME) -> int:
    """Fingerprint of a text from its parts' (hash, length), in order."""
    total, shift = 0, 1
    for h, n in parts:
        total = (total + shift * h) % prime
        shift = shift * pow(base, n, prime) % prime
    return total


def fingerprint(body: bytes, base: int = BASE, prime: int = PRIME) -> int:
    return combine(((chunk_hash(body[i : i + CHUNK], base, prime), min(CHUNK, len(body) - i)) for i in range(0, len(body), CHUNK)), base, prime)


def same(x: bytes, y: bytes) -> bool:
    """Whether two texts are equal, chunk by chunk up to the first difference."""
    return len(x) == len(y) and all(x[i : i + CHUNK] == y[i : i + CHUNK] for i in range(0, len(x), CHUNK))


def normalised(raw: bytes) -> bytes:
    """A-Z lower-cased, nothing else: bytes.lower() changes ASCII letters only."""
    return raw.lower()


def _hashed(docs: DataFrame, text: str, prime: int, digest: bool, body: bool, parallel_bytes: int) -> DataFrame:
    """docs with fp, n_bytes, and if asked for text_sha256 and the normalised bytes."""
    base = BASE % prime
    names = docs.columns
    kind = StructType([*docs.schema.fields]).add("fp", LongType()).add("n_bytes", LongType())
    kind = kind.add("text_sha256", StringType()) if digest else kind
    kind = kind.add("body", BinaryType()) if body else kind

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            texts = [normalised(x.as_buffer().to_pybytes() if x.is_valid else b"") for x in batch.column(batch.num_columns - 1).cast(pa.large_binary())]
            cols = [*batch.columns[:-1], pa.array([fingerprint(x, base, prime) for x in texts], pa.int64()), pa.array([len(x) for x in texts], pa.int64())]
            if digest:
                cols.append(pa.array([hashlib.sha256(x).hexdigest() for x in texts]))
            if body:
                cols.append(pa.array(texts, pa.binary()))
            yield pa.RecordBatch.from_arrays(cols, [*names, "fp", "n_bytes", *["text_sha256"] * digest, *["body"] * body])

    given = docs.select(*[F.col(f"`{c}`") for c in names], F.col(f"`{text}`").alias("hashed text"))
    if body or digest or parallel_bytes <= 0:
        return given.mapInArrow(run, kind)
    short = given.where(F.coalesce(F.octet_length("hashed text"), F.lit(0)) <= parallel_bytes).mapInArrow(run, kind)
    return short.select("fp", "n_bytes").unionByName(_in_chunks(given, parallel_bytes, base, prime))


def _in_chunks(given: DataFrame, parallel_bytes: int, base: int, prime: int) -> DataFrame:
    """fp and n_bytes of texts over parallel_bytes: their chunks are dealt out, hashed in place and summed with their shifts."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            terms = []
            for at, x in zip(batch.column("at").to_pylist(), batch.column("chunk").to_pylist(), strict=True):
                h = combine(((chunk_hash(normalised(x[i : i + CHUNK]), base, prime), len(x[i : i + CHUNK])) for i in range(0, len(x), CHUNK)), base, prime)
                terms.append(h * pow(base, at, prime) % prime)
            yield pa.RecordBatch.from_arrays([batch.column("row"), pa.array(terms, pa.int64()), pa.array([len(x) for x in batch.column("chunk").to_pylist()], pa.int64())], ["row", "term", "n"])

    step = 1 << 20
    long = given.where(F.octet_length("hashed text") > parallel_bytes).select(F.monotonically_increasing_id().alias("row"), F.col("hashed text").cast("binary").alias("b"))
    # all chunks are cut at once: a row for each offset beside the whole text would copy the text once per chunk
    pieces = F.transform(F.sequence(F.lit(0), F.octet_length("b") - 1, F.lit(step)), lambda at: F.struct(at.cast("long").alias("at"), F.substring("b", at + 1, step).alias("chunk")))
    cut = long.select("row", F.explode(pieces).alias("piece")).select("row", "piece.at", "piece.chunk").repartition("row", "at")
    summed = cut.mapInArrow(run, "row long, term long, n long").groupBy("row").agg(F.sum(F.col("term").cast("decimal(38,0)")).alias("t"), F.sum("n").alias("n_bytes"))
    return summed.select((F.col("t") % F.lit(prime).cast("decimal(38,0)")).cast("long").alias("fp"), "n_bytes")


def _bucket() -> Column:
    return F.xxhash64("fp", "n_bytes")


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text: str = "text", payload: bool = False, prime: int = PRIME, parallel_bytes: int = 32 << 20, local_bytes: int = LOCAL_BYTES) -> DataFrame:
    """One row per row of docs: its group of equal texts (equal after lower-casing A-Z).

    Returns id_col (with `payload`, all of docs' columns), keep_id (the largest id of the group),
    group_size, kept, n_bytes and text_sha256. Exactly one row of a group is kept; among rows of the same
    largest id, any one. A null text counts as empty, a null id is smaller than any other; if all ids of
    a group are null, keep_id is null and one row is kept. Empty tables give empty results. Extra columns
    of any name pass through with `payload` and are ignored without.

    Plan: fingerprints of all texts are counted (partial sums per task, so a hot group costs a row per
    task) and those that occur again set bits of a mask of bounded size. A second scan sends on only texts
    whose bit is set. Each task first matches them against texts it holds (`local_bytes` of them), so of
    a group of copies about one text per task is shuffled; these heads meet in fingerprint order, and
    are compared chunk by chunk. False bits cost a shuffle of that text, never a wrong result.
    """
    small_batches(docs)
    columns = docs.columns if payload else [id_col]
    light = docs.select(F.col(f"`{text}`"))
    again = _hashed(light, text, prime, False, False, parallel_bytes).groupBy("fp", "n_bytes").agg(F.count("*").alias("n")).where("n > 1")
    mask = written(mask_of(again, _bucket()), "exact-mask")
    row = F.struct(*[F.col(f"`{c}`") for c in columns]).alias("row")
    scanned = _hashed(docs.select(F.col(f"`{id_col}`").cast("long").alias("id"), row, F.col(f"`{text}`").alias("t")), "t", prime, True, True, 0).drop("t")
    met, alone = masked(scanned, _bucket(), mask)
    alone = alone.select("row", F.col("id").alias("keep_id"), F.lit(1).cast("long").alias("group_size"), F.lit(True).alias("kept"), "n_bytes", "text_sha256")

    heads_kind = StructType([*scanned.select("id", "row", "fp", "n_bytes", "text_sha256", "body").schema.fields]).add("uid", LongType()).add("head", LongType())

    def local(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, n = TaskContext.get().partitionId() << 33, 0
        held: OrderedDict[tuple[int, int], list[tuple[int, bytes]]] = OrderedDict()
        size = 0
        for batch in it:
            body, head, uid = [], [], []
            for key in zip(batch.column("fp").to_pylist(), batch.column("n_bytes").to_pylist(), batch.column("body").to_pylist(), strict=True):
                key, x = key[:2], key[2]
                found = next((u for u, y in held.get(key, ()) if same(x, y)), None)
                uid.append(part + n)
                head.append(part + n if found is None else found)
                body.append(x if found is None else None)
                if found is None:
                    held.setdefault(key, []).append((part + n, x))
                    size += len(x) + 200
                held.move_to_end(key)
                while size > local_bytes and len(held) > 1:
                    size -= sum(len(y) + 200 for _, y in held.popitem(last=False)[1])
                n += 1
            cols = [batch.column(c) for c in ("id", "row", "fp", "n_bytes", "text_sha256")]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(body, pa.binary()), pa.array(uid, pa.int64()), pa.array(head, pa.int64())], heads_kind.names)

    members = written(met.select("id", "row", "fp", "n_bytes", "text_sha256", "body").mapInArrow(local, heads_kind), "exact-members")

    class_kind = StructType().add("uid", LongType()).add("class", LongType())

    def compare(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, known = None, []
        for batch in it:
            out = []
            for fp, n, u, x in zip(*(batch.column(c).to_pylist() for c in ("fp", "n_bytes", "uid", "body")), strict=True):
                if key != (fp, n):
                    key, known = (fp, n), []
                found = next((c for c, y in known if same(x, y)), None)
                if found is None:
                    known.append((found := u, x))
                out.append(found)
            yield pa.RecordBatch.from_arrays([batch.column("uid"), pa.array(out, pa.int64())], class_kind.names)

    heads = members.where("uid = head").select("fp", "n_bytes", "uid", "body").repartition("fp", "n_bytes").sortWithinPartitions("fp", "n_bytes", "uid")
    classed = heads.mapInArrow(compare, class_kind)
    per_head = members.groupBy("head").agg(F.count("*").alias("n"), F.max(F.struct("id", "uid")).alias("top"))
    per_head = written(per_head.join(classed, per_head["head"] == classed["uid"]).select("head", "class", "n", "top"), "exact-heads")
    per_class = per_head.groupBy("class").agg(F.sum("n").alias("group_size"), F.max("top").alias("top"))
    verdict = per_head.join(per_class.select(F.col("class").alias("c"), "group_size", F.col("top").alias("best")), F.col("class") == F.col("c")).select(F.col("head").alias("h"), "group_size", "best")
    grouped = members.join(verdict, F.col("head") == F.col("h")).select("row", F.col("best.id").alias("keep_id"), "group_size", (F.col("uid") == F.col("best.uid")).alias("kept"), "n_bytes", "text_sha256")
    out = alone.unionByName(grouped)
    if payload:
        return out
    return out.select(F.col(f"row.`{id_col}`").alias(id_col), "keep_id", "group_size", "kept", "n_bytes", "text_sha256")


def drop_exact(docs: DataFrame) -> DataFrame:
    """docs without the rows whose text occurs again in a row of a larger doc_id; columns as given."""
    return exact_groups(docs, payload=True).where("kept").select("row.*")


