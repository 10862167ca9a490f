"""Nearest earlier vectors: exact search, inverted cells, sign hashes, and 8-bit codes.

base: (id, seq, vec); queries: (id, seq, vec). All give (q_id, c_id, score) with the k best by cosine of
unit vectors; of equal scores the earliest. causal=True looks only at base rows of a smaller seq, and does so
before the best are chosen.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Queries of a block and base rows of a part: each block meets each part in one task.
BLOCK, PART = 4096, 65_536
#: Base rows of a part that are scored at a time.
SLAB = 2048
#: (queries, rows) -> scores, a row for each query.
Similarity = Callable[[np.ndarray, np.ndarray], np.ndarray]


def cosine(a: Column, b: Column) -> Column:
    """Cosine of two arrays in expressions only; 0 if one has no length."""
    dot = F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)
    norm = lambda v: F.sqrt(F.aggregate(v, F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")))
    return F.coalesce(F.try_divide(dot, norm(a) * norm(b)), F.lit(0.0))


def _matrix(column: pa.Array) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), -1) if len(column) else np.zeros((0, 1), np.float32)


def _dots(q: np.ndarray, m: np.ndarray) -> np.ndarray:
    return q @ m.T


def _best(scores: np.ndarray, k: int) -> np.ndarray:
    """Column numbers of the k greatest of each row and of all that equal the k-th."""
    if scores.shape[1] <= k:
        return np.isfinite(scores)
    kth = -np.partition(-scores, k - 1, axis=1)[:, k - 1 : k]
    return (scores >= kth) & np.isfinite(scores)


def _kept(row: np.ndarray, score: np.ndarray, k: int) -> np.ndarray:
    """Places of the k greatest scores of each row number and of all that equal the k-th."""
    order = np.lexsort((-score, row))
    first = np.searchsorted(row[order], row[order], "left")
    last = np.searchsorted(row[order], row[order], "right") - 1
    return order[score[order] >= score[order][np.minimum(first + k - 1, last)]]


def merged(found: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("q_id").orderBy(F.desc("score"), "c_seq", "c_id")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("q_id", "c_id", "score", "rank")


def exact_topk(queries: DataFrame, base: DataFrame, k: int, causal: bool = True, similarity: Similarity | None = None) -> DataFrame:
    """Every query against every base row: blocks of queries and parts of the base form a grid, and a task takes one field of it.

    Nothing but two row counts reaches the driver. The base is sent to each block, the queries to each part; a
    task holds a block, a part and the scores of a slab. similarity(queries, rows) may replace the dot products.
    """
    blocks = max(1, -(-queries.count() // BLOCK))
    parts = max(base.sparkSession.sparkContext.defaultParallelism, -(-base.count() // PART))
    dealt = queries.select("id", "seq", "vec", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int").alias("block"))
    sent = base.select("id", "seq", "vec", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("block"))
    return merged(_within(dealt, sent, ["block"], k, causal, parts, similarity), k)


def kmeans(sample: np.ndarray, cells: int, rounds: int = 12, seed: int = 3) -> np.ndarray:
    """Unit centroids of unit vectors. Empty cells are given the worst-served vectors."""
    rng = np.random.default_rng(seed)
    c = sample[rng.choice(len(sample), min(cells, len(sample)), replace=False)].astype(np.float64)
    for _ in range(rounds):
        s = sample @ c.T
        own = s.argmax(1)
        sums = np.zeros_like(c)
        np.add.at(sums, own, sample)
        empty = np.flatnonzero(np.bincount(own, minlength=len(c)) == 0)
        if len(empty):
            sums[empty] = sample[np.argsort(s.max(1))[: len(empty)]]
        c = sums / np.maximum(np.linalg.norm(sums, axis=1, keepdims=True), 1e-12)
    return c.astype(np.float32)


def ivf_build(base: DataFrame, cells: int, per_cell: int = 256, seed: int = 3) -> tuple[np.ndarray, DataFrame]:
    """Centroids from a bounded sample (per_cell vectors a cell), and base with its nearest cell."""
    rows = base.orderBy(F.xxhash64("id"), "id").limit(cells * per_cell).select("vec").collect()
    centroids = kmeans(np.array([r[0] for r in rows], np.float32), cells, seed=seed) if rows else np.zeros((1, 1), np.float32)
    return centroids, with_cells(base, centroids, 1)


def with_cells(vectors: DataFrame, centroids: np.ndarray, nprobe: int) -> DataFrame:
    """A row for each of a vector's nprobe nearest cells. New vectors join existing cells this way."""
    shared = vectors.sparkSession.sparkContext.broadcast(centroids)

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = shared.value
        n = min(nprobe, len(c))
        for b in it:
            if b.num_rows:
                cell = np.argsort(-(_matrix(b.column("vec")) @ c.T), axis=1, kind="stable")[:, :n]
                at = pa.array(np.repeat(np.arange(b.num_rows), n))
                yield pa.RecordBatch.from_arrays([*(col.take(at) for col in b.columns), pa.array(cell.ravel().astype(np.int32))], [*b.schema.names, "cell"])

    v = vectors.select("id", "seq", "vec")
    return v.mapInArrow(run, f"{', '.join(f'{n} {t}' for n, t in v.dtypes)}, cell int")


def _within(left: DataFrame, right: DataFrame, keys: list[str], k: int, causal: bool, salts: int = 1, similarity: Similarity | None = None) -> DataFrame:
    """Best pairs of rows of equal keys. Base rows of a key are spread over `salts` groups, queries are sent to each."""
    # columns of their own on both sides, which may come from one table
    left, right = (df.select(*[F.col(c).alias(c) for c in df.columns]) for df in (left, right))
    spread = right.withColumn("salt", F.pmod(F.xxhash64("id"), F.lit(salts)).cast("int"))
    sent = left.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    kind = right.schema["id"].dataType.simpleString()

    def run(q: pa.Table, c: pa.Table) -> pa.Table:
        schema = pa.schema([("q_id", q.schema.field("id").type), ("c_id", q.schema.field("id").type), ("c_seq", pa.int64()), ("score", pa.float64())])
        if not q.num_rows or not c.num_rows:
            return schema.empty_table()
        qv = _matrix(q.column("vec").combine_chunks()).astype(np.float64)
        cv, c_seq, q_seq = _matrix(c.column("vec").combine_chunks()), c.column("seq").to_numpy(), q.column("seq").to_numpy()
        i, j, s = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
        for at in range(0, len(cv), SLAB):
            part = np.round((similarity or _dots)(qv, cv[at : at + SLAB].astype(np.float64)), 9)
            if causal:
                part = np.where(c_seq[None, at : at + SLAB] < q_seq[:, None], part, -np.inf)
            row, col = np.nonzero(_best(part, k))
            i, j, s = np.append(i, row), np.append(j, col + at), np.append(s, part[row, col])
            best = _kept(i, s, k)
            i, j, s = i[best], j[best], s[best]
        return pa.table([q.column("id").take(pa.array(i)), c.column("id").take(pa.array(j)), c.column("seq").take(pa.array(j)), pa.array(s)], schema=schema)

    by = [*keys, "salt"]
    return sent.groupBy(*by).cogroup(spread.groupBy(*by)).applyInArrow(run, f"q_id {kind}, c_id {kind}, c_seq long, score double")


def ivf_topk(queries: DataFrame, cells: DataFrame, centroids: np.ndarray, k: int, nprobe: int, causal: bool = True, salts: int = 1) -> DataFrame:
    """The best within each query's nprobe nearest cells; with all cells the same as exact_topk."""
    return merged(_within(with_cells(queries, centroids, nprobe), cells, ["cell"], k, causal, salts), k)


def plane_signs(planes: int, width: int, seed: int = 1) -> np.ndarray:
    """Planes with whole-number coordinates from -500 to 500 by an arithmetic rule, so that SQL can write them too."""
    p, d = np.arange(planes)[:, None], np.arange(width)[None, :]
    return ((p * 7919 + d * 104729 + p * d * 31 + seed * 1299709) % 1_000_003 % 1001 - 500).astype(np.float64)


def lsh_keys(vectors: DataFrame, bits: int, tables: int, width: int, seed: int = 1) -> DataFrame:
    """(id, seq, vec, tab, bucket): for each table, the signs of `bits` projections as a number."""
    planes = plane_signs(bits * tables, width, seed)
    shared = vectors.sparkSession.sparkContext.broadcast(planes)

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            if b.num_rows:
                on = (_matrix(b.column("vec")).astype(np.float64) @ shared.value.T > 0).reshape(-1, tables, bits)
                bucket = (on * (1 << np.arange(bits))).sum(2).astype(np.int64)
                at = pa.array(np.repeat(np.arange(b.num_rows), tables))
                yield pa.RecordBatch.from_arrays([*(col.take(at) for col in b.columns), pa.array(np.tile(np.arange(tables, dtype=np.int32), b.num_rows)), pa.array(bucket.ravel())], [*b.schema.names, "tab", "bucket"])

    v = vectors.select("id", "seq", "vec")
    return v.mapInArrow(run, f"{', '.join(f'{n} {t}' for n, t in v.dtypes)}, tab int, bucket long")


def lsh_topk(queries: DataFrame, base: DataFrame, k: int, bits: int = 8, tables: int = 8, width: int = 64, causal: bool = True, seed: int = 1, salts: int = 1) -> DataFrame:
    """The best among base rows that share a bucket with the query in some table, scored exactly."""
    found = _within(lsh_keys(queries, bits, tables, width, seed), lsh_keys(base, bits, tables, width, seed), ["tab", "bucket"], k, causal, salts)
    return merged(found.dropDuplicates(["q_id", "c_id"]), k)


def sq8_range(base: DataFrame) -> DataFrame:
    """Smallest and greatest value of each place, as one row of two arrays."""
    each = base.select(F.posexplode("vec").alias("d", "x")).groupBy("d").agg(F.min("x").alias("low"), F.max("x").alias("high"))
    s = each.agg(F.sort_array(F.collect_list(F.struct("d", "low", "high"))).alias("s"))
    return s.select(F.transform("s", lambda x: x["low"]).alias("low"), F.transform("s", lambda x: x["high"]).alias("high"))


def sq8_topk(queries: DataFrame, base: DataFrame, k: int, widen: int = 10, causal: bool = True) -> DataFrame:
    """Search over vectors kept as a byte per place, then exact scores of the best widen * k. A quarter of the bytes are scanned."""
    row = sq8_range(base).first()
    low = np.array(row["low"], np.float32)
    step = (np.array(row["high"], np.float32) - low) / 255
    codes = sq8_encode(base, low, step)
    rough = exact_topk(queries, sq8_decode(codes, low, step), k * widen, causal).select("q_id", "c_id")
    q, c = queries.select(F.col("id").alias("q_id"), F.col("vec").alias("qv")), base.select(F.col("id").alias("c_id"), F.col("seq").alias("c_seq"), F.col("vec").alias("cv"))
    return merged(rough.join(q, "q_id").join(c, "c_id").select("q_id", "c_id", "c_seq", F.round(cosine(F.col("qv"), F.col("cv")), 9).alias("score")), k)


def sq8_encode(base: DataFrame, low: np.ndarray, step: np.ndarray) -> DataFrame:
    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            m = _matrix(b.column("vec"))
            code = np.clip(np.round((m - low) / np.where(step > 0, step, 1)), 0, 255).astype(np.uint8) if b.num_rows else m
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("seq"), pa.array([r.tobytes() for r in code], pa.binary())], ["id", "seq", "code"])

    v = base.select("id", "seq", "vec")
    return v.mapInArrow(run, f"id {v.schema['id'].dataType.simpleString()}, seq long, code binary")


def sq8_decode(codes: DataFrame, low: np.ndarray, step: np.ndarray) -> DataFrame:
    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            m = np.frombuffer(b"".join(b.column("code").to_pylist()), np.uint8).reshape(b.num_rows, -1) * step + low if b.num_rows else np.zeros((0, 1), np.float32)
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("seq"), pa.array(list(m.astype(np.float32)), pa.list_(pa.float32()))], ["id", "seq", "vec"])

    return codes.mapInArrow(run, f"id {codes.schema['id'].dataType.simpleString()}, seq long, vec array<float>")


def recall(found: DataFrame, exact: DataFrame) -> DataFrame:
    """Share of the exact best that were found."""
    hit = exact.join(found.select("q_id", "c_id"), ["q_id", "c_id"], "left_semi").agg(F.count("*").alias("hits"))
    return exact.agg(F.count("*").alias("wanted")).join(F.broadcast(hit), F.lit(True)).select("wanted", "hits", F.round(F.try_divide(F.col("hits").cast("double"), F.col("wanted").cast("double")), 6).alias("recall"))
