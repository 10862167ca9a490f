"""Best-fit packing by minimum bin slack: the fullest feasible combination of lengths per sequence, by bitset subset sums.

Only the counts of each length are needed to choose combinations, so the choice works on a histogram of
at most `size` rows, whatever the number of documents. Pieces then find their place by their rank among
pieces of equal length.
"""

from __future__ import annotations

import base64
import json
import re
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tracegroup.llm import bytehash
from tracegroup.llm.common import bytes_of, slices, small_batches, written

SIZE = 2048
#: Text bytes that are tokenised at a time: arrays of positions take many times as much.
SLICE = 1 << 19


class WordTokens:
    """Token ids of the public byte-level BPE for many texts at once, each distinct word being encoded once.

    The vocabulary's splitting pattern never joins text across one space or line feed that stands between
    signs that are not white space, so a text without other white space runs is the sequence of its words,
    each with the space or line feed before it. Words are told apart by a 64-bit hash and remembered in
    a table of bounded size. Other texts, and those with a special token's string, are encoded whole.
    """

    SLOT_BITS = 20
    MOST = 3_000_000
    LINE_FEED = 198  # the vocabulary's id of a line feed

    def __init__(self, json_path: str | None = None, rank_path: str | None = None):
        import public_tokenizers
        import tiktoken

        self.json_path, self.whole = json_path or public_tokenizers.path("byte_bpe_50k.json"), None
        with open(rank_path or public_tokenizers.path("byte_bpe_50k.tiktoken"), "rb") as lines:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
        self.words = tiktoken.Encoding("byte_bpe", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
        with open(self.json_path, encoding="utf-8") as file:
            described = file.read()
        at = re.search(r'"added_tokens"\s*:\s*', described).end()
        self.special = [t["content"].encode() for t in json.JSONDecoder().raw_decode(described, at)[0]]
        self.rest()

    def rest(self) -> None:
        """Hold the vocabulary only: a worker that waits or does other work keeps no table of words."""
        self.key = self.begin = self.count = None
        self.ids = np.zeros(0, np.uint32)

    def _forget(self) -> None:
        slots = 1 << self.SLOT_BITS
        self.key, self.begin, self.count = np.zeros(slots, np.uint64), np.zeros(slots, np.int32), np.zeros(slots, np.int32)
        self.ids = np.zeros(0, np.uint32)

    def one(self, body: bytes) -> np.ndarray:
        text = body.decode()
        if any(s in body for s in self.special):
            if self.whole is None:  # few texts need it, and it takes much memory
                from tokenizers import Tokenizer

                self.whole = Tokenizer.from_file(self.json_path)
            return np.array(self.whole.encode(text, add_special_tokens=False).ids, np.uint32)
        return np.array(self.words.encode_ordinary(text), np.uint32)

    def _learn(self, keys: np.ndarray, bodies: list[bytes], lead: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Encode new words in one call, a line each; lead says which of them a line feed precedes. Gives their places in ids."""
        got = np.array(self.words.encode_ordinary(b"\n".join(bodies).decode()), np.uint32)
        ends = np.append(np.flatnonzero(got == self.LINE_FEED), len(got))
        starts = np.concatenate([[0], ends[:-1] + 1])
        if len(ends) != len(bodies):
            raise ValueError("a word was joined with its neighbour")
        # with the line feed before it, a word begins one place earlier; the first has one put before it
        begin, count = starts + 1 - lead + len(self.ids), ends - starts + lead
        self.ids = np.concatenate([self.ids, [np.uint32(self.LINE_FEED)], got])
        slot = (keys >> np.uint64(64 - self.SLOT_BITS)).astype(np.int64)
        self.key[slot], self.begin[slot], self.count[slot] = keys, begin, count  # of words in one slot the last stays
        return begin, count

    def encode(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """All rows' ids, one row after another, and where each row's begin."""
        rows = len(offsets) - 1
        odd = self._odd(data, offsets)
        start, end, row = bytehash.spans(data, offsets, _IN_WORD)
        keep = ~odd[row]
        start, end, row = start[keep], end[keep], row[keep]
        before = np.where(start == offsets[row], 0, data[np.maximum(start - 1, 0)])
        key = bytehash.token_hashes(data, start, end) ^ _LEAD[before]
        if self.key is None or len(self.ids) > self.MOST:
            self._forget()
        slot = (key >> np.uint64(64 - self.SLOT_BITS)).astype(np.int64)
        begin, count = self.begin[slot].astype(np.int64), self.count[slot].astype(np.int64)
        new = np.flatnonzero(self.key[slot] != key)
        if len(new):
            distinct, at, back = np.unique(key[new], return_index=True, return_inverse=True)
            first, raw = new[at], data.tobytes()
            low = start[first] - (before[first] == 32)
            found = self._learn(distinct, [raw[a:b] for a, b in zip(low.tolist(), end[first].tolist(), strict=True)], (before[first] == 10).astype(np.int64))
            begin[new], count[new] = found[0][back], found[1][back]
        total = np.concatenate([[0], np.cumsum(count)])
        ids = self.ids[np.repeat(begin - total[:-1], count) + np.arange(total[-1])] if len(count) else np.zeros(0, np.uint32)
        size = np.bincount(row, count, rows).astype(np.int64)
        cut = np.concatenate([[0], np.cumsum(size)])
        if odd.any():
            parts = [self.one(data[offsets[i] : offsets[i + 1]].tobytes()) if odd[i] else ids[cut[i] : cut[i + 1]] for i in range(rows)]
            cut = np.concatenate([[0], np.cumsum([len(x) for x in parts])])
            ids = np.concatenate(parts)
        return ids, cut

    def _odd(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Rows that begin or end with white space, have white space beside white space, or a special token's string."""
        white = _WHITE[data]
        for lead, follow in _WIDE:
            hit = np.flatnonzero(data == lead[0])
            hit = hit[hit + len(lead) < len(data)]
            for i, b in enumerate(lead[1:], 1):
                hit = hit[data[hit + i] == b]
            hit = hit[np.isin(data[hit + len(lead)], follow)]
            for i in range(len(lead) + 1):
                white[hit + i] = True
        odd = np.zeros(len(offsets) - 1, bool)
        pair = np.flatnonzero(white[:-1] & white[1:])
        left, right = np.searchsorted(offsets, pair, "right") - 1, np.searchsorted(offsets, pair + 1, "right") - 1
        odd[left[left == right]] = True
        full = np.flatnonzero(np.diff(offsets))
        odd[full[white[offsets[full]] | white[offsets[full + 1] - 1]]] = True
        raw = data.tobytes()
        for s in self.special:
            i = raw.find(s)
            while i >= 0:
                odd[np.searchsorted(offsets, i, "right") - 1] = True
                i = raw.find(s, i + 1)
        return odd


_IN_WORD = np.ones(256, np.uint8)
_IN_WORD[[10, 32]] = 0
#: What Unicode counts as white space, in UTF-8: single bytes, and lead bytes with their last bytes.
_WHITE = np.zeros(256, bool)
_WHITE[[9, 10, 11, 12, 13, 28, 29, 30, 31, 32]] = True
_WIDE = (((0xC2,), [0x85, 0xA0]), ((0xE1, 0x9A), [0x80]), ((0xE2, 0x80), [*range(0x80, 0x8B), 0xA8, 0xA9, 0xAF]), ((0xE2, 0x81), [0x9F]), ((0xE3, 0x80), [0x80]))
_LEAD = np.zeros(256, np.uint64)
_LEAD[32], _LEAD[10] = 0x9D8F3A6B5C1E7042, 0x3C6EF372FE94F82B


@lru_cache(maxsize=2)
def _tokens(json_path: str | None, rank_path: str | None) -> WordTokens:
    return WordTokens(json_path, rank_path)


def tokenised(it: Iterator[pa.RecordBatch], tokens: WordTokens) -> Iterator[tuple[pa.Array, np.ndarray, np.ndarray]]:
    """(document ids, token ids, where each document's begin) of slices of the batches' texts; at the end the words are forgotten."""
    try:
        for batch in it:
            data, offsets = bytes_of(batch.column("t"))
            for a, b in slices(offsets, SLICE):
                yield batch.column("id").slice(a, b - a), *tokens.encode(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
    finally:
        tokens.rest()


def pieces(docs: DataFrame, id_col: str = "doc_id", text: str = "text", size: int = SIZE, json_path: str | None = None, rank_path: str | None = None) -> DataFrame:
    """Per piece of at most `size` tokens: id, piece, start, length, ids_crc32, and the task and place among its pieces of this length.

    A document is its ids and a closing id 0, so an empty or null text is one token. A longer one is cut so
    that all pieces but the first are full.
    """

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen, part = Counter(), TaskContext.get().partitionId()
        for found in tokenised(it, _tokens(json_path, rank_path)):
            yield cut(*found, seen, part)

    def cut(doc: pa.Array, ids: np.ndarray, cuts: np.ndarray, seen: Counter, part: int) -> pa.RecordBatch:
        raw, out = memoryview(ids.astype("<u4").tobytes()), []
        for row, (low, high) in enumerate(zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)):
            n = high - low + 1
            ends = range(n % size or size, n + 1, size)
            start = 0
            for k, end in enumerate(ends):
                crc = zlib.crc32(raw[4 * (low + start) : 4 * (low + min(end, n - 1))])
                out.append((row, k, start, end - start, zlib.crc32(bytes(4), crc) if end == n else crc, seen[end - start]))
                seen[end - start] += 1
                start = end
        row, *cols = zip(*out, strict=True)
        return pa.RecordBatch.from_arrays([doc.take(pa.array(row)), pa.array(cols[0], pa.int32()), *(pa.array(c, pa.int64()) for c in cols[1:]), pa.array(np.full(len(row), part), pa.int32())], ["id", "piece", "start", "length", "ids_crc32", "nth", "task"])

    given = small_batches(docs).select(F.col(f"`{id_col}`").cast("long").alias("id"), F.col(f"`{text}`").alias("t"))
    return given.mapInArrow(run, "id long, piece int, start long, length long, ids_crc32 long, nth long, task int")


@dataclass
class Plan:
    """Combinations in use: for each length, ranks from `upto[i-1]` to `upto[i]` go to slot i."""

    upto: dict[int, np.ndarray]
    slots: dict[int, np.ndarray]  # rows: first sequence, copies in a sequence, offset of the first copy
    sequences: int


def fullest(counts: dict[int, int], seed: int, size: int) -> list[int]:
    """The seed length and those lengths that fill a sequence most, lengths being used at most as often as there are pieces.

    reach is a bitset of sums within reach; each length is added copy by copy until the room is filled exactly.
    """
    room = size - seed
    full, reach = (1 << (room + 1)) - 1, 1
    steps: list[tuple[int, int]] = []
    for length in sorted((x for x in counts if x <= room), reverse=True):
        for _ in range(min(counts[length] - (length == seed), room // length)):
            more = (reach | reach << length) & full
            if more == reach:
                break
            steps.append((length, reach))
            reach = more
            if reach >> room & 1:
                break
        if reach >> room & 1:
            break
    total, out = reach.bit_length() - 1, [seed]
    for length, before in reversed(steps):
        if not before >> total & 1:
            out.append(length)
            total -= length
    return out


def minimum_bin_slack(histogram: dict[int, int], size: int = SIZE) -> Plan:
    """Fill sequence by sequence: the largest length left and the fullest combination beside it, repeated as often as the counts allow."""
    left = {x: n for x, n in histogram.items() if n > 0}
    used: Counter[int] = Counter()
    rows: dict[int, list[tuple[int, int, int, int]]] = {x: [] for x in left}
    sequences = 0
    while left:
        chosen = Counter(fullest(left, max(left), size))
        times = min(left[x] // n for x, n in chosen.items())
        at = 0
        for x in sorted(chosen, reverse=True):
            n = chosen[x]
            used[x] += n * times
            rows[x].append((used[x], sequences, n, at))
            at += n * x
            left[x] -= n * times
            if not left[x]:
                del left[x]
        sequences += times
    return Plan({x: np.array([r[0] for r in v], np.int64) for x, v in rows.items()}, {x: np.array([r[1:] for r in v], np.int64) for x, v in rows.items()}, sequences)


def pack(docs: DataFrame, id_col: str = "doc_id", text: str = "text", size: int = SIZE, **paths) -> DataFrame:
    """pieces() with sequence_id and offset: every piece placed, every sequence gapless from offset 0 and at most `size` tokens.

    The pieces (a few numbers each) are written once. Ranks among equal lengths come from counts per task,
    so no length is gathered, however many pieces have it; the counts of lengths, `size` rows at most, go
    to the driver, and the plan back to the tasks. Empty tables give empty results.
    """
    spark = docs.sparkSession
    table = written(pieces(docs, id_col, text, size, **paths), "pieces")
    per_task = table.groupBy("length", "task").agg(F.count("*").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.partitionBy("length").orderBy("task").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = written(per_task.select("length", "task", "n", before.alias("before")), "piece-ranks")
    histogram = {r["length"]: r["n"] for r in starts.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    shared = spark.sparkContext.broadcast(minimum_bin_slack(histogram, size))

    def place(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        plan = shared.value
        for batch in it:
            length, rank = batch.column("length").to_numpy(), batch.column("rank").to_numpy()
            sequence, offset = np.empty(len(length), np.int64), np.empty(len(length), np.int64)
            for x in np.unique(length):
                rows = np.flatnonzero(length == x)
                upto, slots = plan.upto[int(x)], plan.slots[int(x)]
                i = np.searchsorted(upto, rank[rows], "right")
                first, copies, at = slots[i].T
                k = rank[rows] - np.where(i > 0, upto[i - 1], 0)
                sequence[rows] = first + k // copies
                offset[rows] = at + (k % copies) * x
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("id", "piece", "start", "length", "ids_crc32")), pa.array(sequence), pa.array(offset)], ["id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    ranked = table.join(starts.select("length", "task", "before"), ["length", "task"]).select("id", "piece", "start", "length", "ids_crc32", (F.col("nth") + F.col("before")).alias("rank"))
    out = ranked.mapInArrow(place, "id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
    return out.withColumnRenamed("id", id_col)


