"""Removal of long byte strings that occur again, by a suffix sort whose comparisons look up prefix hashes.

Two equal strings of `length` bytes have the same smallest k-gram hash at the same place: their anchor.
The strings of an anchor are taken in ranges of STEP starts. All strings of a range share a core; beyond
it a string has some bytes on the left and the others on the right. Ranges with equal cores are merge-sorted by
what follows the core: polynomial prefix hashes and a binary search give the common extension of two
suffixes in a logarithmic number of steps. Cores are compared by a second, cryptographic digest and
the bytes around them as bytes before anything is removed.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tracegroup.llm import bytehash
from tracegroup.llm.common import bytes_of, mask_of, masked, slices, small_batches, written

LENGTH = 400
#: Bytes of the k-grams that anchors are chosen from.
GRAM = 128
#: Starts of a range: strings of a range share length - STEP + 1 bytes.
STEP = 32
#: Bytes of texts whose anchors are looked for at a time.
SLICE_BYTES = 1 << 19
#: Ranges that are sorted together.
ROWS = 12_000
#: Ranges of one core that a task holds; those of a core with more are compared string by string, by counts of digests.
HOT = 32_768


def sliding(f: np.ufunc, a: np.ndarray, w: int, fill: int) -> np.ndarray:
    """f over every run of w entries: from each block's running values backwards and the next block's forwards."""
    n = len(a) - w + 1
    if n <= 0:
        return a[:0]
    padded = np.full(-(-len(a) // w) * w, fill, a.dtype)
    padded[: len(a)] = a
    grid = padded.reshape(-1, w)
    ahead = f.accumulate(grid, axis=1).ravel()
    behind = f.accumulate(grid[:, ::-1], axis=1)[:, ::-1].ravel()
    return f(behind[:n], ahead[w - 1 : w - 1 + n])


def owned_anchors(data: np.ndarray, offsets: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Places of k-grams that are the first smallest of a string of `length` bytes within a row, their hashes, and the first and last start of such strings."""
    w = length - gram + 1
    n = len(data) - gram + 1
    none = np.zeros(0, np.int64)
    if n < w:
        return none, none.view(np.uint64), none, none
    pre = bytehash.prefix(data)
    at = np.arange(n)
    h = bytehash.mix(bytehash.ranges(pre, at, at + gram))
    least = sliding(np.minimum, h, w, (1 << 64) - 1)
    ends = np.zeros(len(data) + 1, np.int32)  # starts whose string leaves its row are not looked at
    for_rows = offsets[1:]
    np.add.at(ends, np.maximum(for_rows - length + 1, offsets[:-1]), 1)
    np.add.at(ends, for_rows, -1)
    least[np.cumsum(ends)[: len(least)] > 0] = 0
    padded = np.zeros(n + w - 1, np.uint64)
    padded[w - 1 : w - 1 + len(least)] = least
    most = sliding(np.maximum, padded, w, 0)
    place = np.flatnonzero((most == h[: len(most)]) & (h[: len(most)] > 0))
    # starts with the same smallest hash follow one another; of those over a place, one such run is its own
    first = np.flatnonzero(np.concatenate([[True], least[1:] != least[:-1]]))
    last = np.append(first[1:], len(least)) - 1
    run = np.searchsorted(first, np.maximum(place - w + 1, 0), "right") - 1
    while (wrong := least[first[run]] != h[place]).any():
        run += wrong
    low, high = np.maximum(first[run], place - w + 1), np.minimum(last[run], place)
    # of equal smallest hashes the first one in a string is its anchor, so each string has one
    low[1:] = np.where(run[1:] == run[:-1], np.maximum(low[1:], place[:-1] + 1), low[1:])
    own = low <= high
    return place[own], h[place[own]], low[own], high[own]


def anchors(data: np.ndarray, offsets: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, np.ndarray]:
    """Places and hashes of owned_anchors()."""
    return owned_anchors(data, offsets, length, gram)[:2]


def _pieces(n: int, length: int) -> Iterator[tuple[int, int]]:
    """A very long text in overlapping parts: every string of `length` bytes is inside one."""
    for a in range(0, max(n - length + 1, 1), SLICE_BYTES):
        yield a, min(n, a + SLICE_BYTES + length - 1)


def _anchor_rows(docs: DataFrame, length: int, gram: int) -> DataFrame:
    """(hash, k1, k2, pos, low, high) of every anchor of the texts, once for most texts that a task has met before."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        met = np.zeros((1 << 16, 2), np.int64)
        for batch in it:
            data, offsets = bytes_of(batch.column("t"))
            k1, k2 = batch.column("k1").to_numpy(), batch.column("k2").to_numpy()
            for a, b in slices(offsets, SLICE_BYTES):
                fresh = np.ones(b - a, bool)
                for i in range(a, b):
                    slot = k1[i] & 0xFFFF
                    fresh[i - a] = met[slot, 0] != k1[i] or met[slot, 1] != k2[i]
                    met[slot] = k1[i], k2[i]
                if not fresh.any():
                    continue
                for x, y in _pieces(offsets[b] - offsets[a], length) if b - a == 1 else [(0, offsets[b] - offsets[a])]:
                    off = np.array([0, y - x]) if b - a == 1 else offsets[a : b + 1] - offsets[a]
                    place, h, low, high = owned_anchors(data[offsets[a] + x : offsets[a] + y], off, length, gram)
                    row = np.searchsorted(off, place, "right") - 1
                    keep = fresh[row] if len(row) else np.zeros(0, bool)
                    place, row, h, low, high = place[keep], row[keep], h[keep], low[keep], high[keep]
                    if len(place):
                        base = off[row] - x
                        yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(k1[a:b][row]), pa.array(k2[a:b][row]), pa.array(place - base), pa.array(low - base), pa.array(high - base)], ["hash", "k1", "k2", "pos", "low", "high"])

    return docs.where(F.octet_length("t") >= length).select("k1", "k2", "t").mapInArrow(run, "hash long, k1 long, k2 long, pos long, low long, high long")


class Extensions:
    """Common extensions of suffixes in one buffer of regions, by binary search over prefix hashes."""

    def __init__(self, data: np.ndarray):
        self.data, self.pre = data, bytehash.prefix(data)
        bytehash.powers(len(data) + 1)

    def common(self, x: np.ndarray, y: np.ndarray, most: np.ndarray) -> np.ndarray:
        """Length of the longest common run from x and from y, at most `most`."""
        low, high = np.zeros_like(most), most.copy()
        for _ in range(int(most.max(initial=0)).bit_length()):
            mid = (low + high + 1) >> 1
            equal = bytehash.ranges(self.pre, x, x + mid) == bytehash.ranges(self.pre, y, y + mid)
            low, high = np.where(equal, mid, low), np.where(equal, high, mid - 1)
        return low

    def before(self, x: np.ndarray, y: np.ndarray, ends: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Whether suffix x of region i sorts before suffix y of region j."""
        n = self.common(x, y, np.minimum(ends[i] - x, ends[j] - y))
        out, other = x + n >= ends[i], y + n >= ends[j]
        a = np.where(out, -1, self.data[np.minimum(x + n, len(self.data) - 1)].astype(np.int64))
        b = np.where(other, -1, self.data[np.minimum(y + n, len(self.data) - 1)].astype(np.int64))
        return a < b


def sort_suffixes(ext: Extensions, group: np.ndarray, start: np.ndarray, region: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Order of the suffixes by group (given sorted), then by their bytes up to their region's end.

    Merge sort from runs of one, all merges of a round at once: each suffix finds its rank in the other
    run by binary search, and each comparison is a common extension.
    """
    n = len(group)
    order = np.arange(n)
    first = np.searchsorted(group, group, "left")
    size = np.searchsorted(group, group, "right") - first
    width = 1
    while n and width < size.max():
        at = np.flatnonzero(size > width)  # places that still take part
        inner = at - first[at]
        run = inner // width
        pair = first[at] + (run // 2) * 2 * width
        end = first[at] + size[at]
        left = run % 2 == 0
        low = np.where(left, np.minimum(pair + width, end), pair)
        high = np.where(left, np.minimum(pair + 2 * width, end), np.minimum(pair + width, end))
        begin = low.copy()
        me = order[at]
        while (open_ := np.flatnonzero(low < high)).size:
            mid = (low[open_] + high[open_]) >> 1
            other, own = order[mid], me[open_]
            lt = ext.before(start[other], start[own], ends, region[other], region[own])
            gt = ext.before(start[own], start[other], ends, region[own], region[other])
            goes = np.where(left[open_], lt, ~gt)  # equal ones of the left run come first
            low[open_] = np.where(goes, mid + 1, low[open_])
            high[open_] = np.where(goes, high[open_], mid)
        own_rank = inner - run * width
        new = order.copy()
        new[pair + own_rank + (low - begin)] = me
        order = new
        width *= 2
    return order


def repeated_strings(group: np.ndarray, left: np.ndarray, right: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """Per range, for each number of bytes on the left of the core: whether another range of its group (sorted) has the same string.

    left, right: the bytes before and after the core, one row each; low, high: the numbers for which a range has a string.
    """
    rows, wide = left.shape
    step = wide + 1
    found = np.zeros((rows, step), bool)
    if not rows:
        return found
    sides = np.concatenate([left, right], 1)
    ext = Extensions(np.ascontiguousarray(sides).ravel())
    begin = np.arange(rows) * 2 * wide
    has = np.arange(step) >= low[:, None]
    has &= np.arange(step) <= high[:, None]
    # ranges that agree in all bytes are one class, all of whose strings occur again
    name = bytehash.mix(bytehash.ranges(ext.pre, begin, begin + 2 * wide) + group.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) + (low * 64 + high).astype(np.uint64)
    _, first, back, times = np.unique(name, return_index=True, return_inverse=True, return_counts=True)
    like = first[back]
    if not ((sides == sides[like]).all() and (group == group[like]).all() and (low == low[like]).all() and (high == high[like]).all()):
        whole = np.concatenate([group.astype(np.int64)[:, None], low[:, None], high[:, None], sides], 1)  # a collision: compare them as they are
        _, first, back, times = np.unique(whole, axis=0, return_index=True, return_inverse=True, return_counts=True)
        back = back.ravel()
    one = first[np.argsort(first)]
    of = np.empty(len(first), np.int64)
    of[np.argsort(first)] = np.arange(len(first))
    many = times[np.argsort(first)] > 1
    mine = np.zeros((len(one), step), bool)
    mine[many] = has[one][many]
    # groups of several classes: suffixes after the core in order, and what they share with their neighbours
    own = group[one]
    _, at, size = np.unique(own, return_inverse=True, return_counts=True)
    mixed = np.flatnonzero(size[at] > 1)
    if len(mixed):
        rows_ = one[mixed]
        start, ends = begin[rows_] + wide, begin[rows_] + 2 * wide
        order = sort_suffixes(ext, own[mixed], start, np.arange(len(mixed)), ends)
        rows_, cls = rows_[order], mixed[order]
        differs = right[rows_[1:]] != right[rows_[:-1]]
        lcp = np.where(differs.any(1), differs.argmax(1), wide)
        lcp[group[rows_[1:]] != group[rows_[:-1]]] = -1
        gap = np.concatenate([[-1], lcp])
        before = np.zeros(len(rows_), np.int64)
        for n in range(step):
            if n:
                before = np.unique(before * 256 + left[rows_, wide - n], return_inverse=True)[1]
            valid = np.flatnonzero(has[rows_, n])
            key = np.cumsum(gap < wide - n) * (len(rows_) + 1) + before
            _, to, count = np.unique(key[valid], return_inverse=True, return_counts=True)
            mine[cls[valid[count[to] > 1]], n] = True
    return mine[of[back]]


def _ranges(texts: DataFrame, length: int) -> DataFrame:
    """(g, core, k1, k2, last, low, high, left, right) of each range of starts at the anchors of texts (k1, k2, t, places).

    g and core are the prefix hash and the digest of the bytes that all strings of the range share, from `last` on; low and
    high say how many bytes more on the left its strings have; left and right are the STEP - 1 bytes around the core (0 beyond the text).
    """
    wide, shared = STEP - 1, length - STEP + 1

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            data, offsets = bytes_of(batch.column("t"))
            k1, k2 = batch.column("k1").to_numpy(), batch.column("k2").to_numpy()
            lists = batch.column("places")
            cut = lists.offsets.to_numpy() - lists.offsets[0].as_py()
            pos, first, last = (lists.flatten().field(c).to_numpy() for c in ("pos", "low", "high"))
            for a, b in slices(offsets):
                x, y = cut[a], cut[b]
                p, f, z = pos[x:y], first[x:y], last[x:y]
                row = np.repeat(np.arange(a, b), np.diff(cut[a : b + 1]))
                near, far = (p - z) // STEP, (p - f) // STEP
                for u in range(0, len(p), ROWS):  # a very long text has many anchors
                    v = slice(u, u + ROWS)
                    times = far[v] - near[v] + 1
                    i = np.repeat(np.arange(len(times)), times)
                    k = near[v][i] + np.arange(len(i)) - np.repeat(np.cumsum(times) - times, times)
                    yield rows(data, offsets, k1, k2, row[v][i], p[v][i], f[v][i], z[v][i], k)

    def rows(data, offsets, k1, k2, row, p, first, last, k) -> pa.RecordBatch:
        begin, end = offsets[row], offsets[row + 1]
        at = begin + p - k * STEP
        low, high = np.maximum(0, p - last - k * STEP), np.minimum(wide, p - first - k * STEP)
        around = []
        for i in (at[:, None] + np.arange(-wide, 0), at[:, None] + shared + np.arange(wide)):
            inside = (i >= begin[:, None]) & (i < end[:, None])
            around.append(np.where(inside, data[np.clip(i, 0, max(len(data) - 1, 0))], 0).astype(np.uint8))
        base = int(at.min()) if len(at) else 0
        part = data[base : int(at.max()) + shared] if len(at) else data[:0]
        g, raw = np.empty(len(at), np.uint64), memoryview(np.ascontiguousarray(part))
        order = np.argsort(at, kind="stable")
        for u in range(0, len(at), 4096):  # prefix hashes over a few texts at a time
            o = order[u : u + 4096]
            here = at[o[0]]
            if at[o[-1]] - here > 1 << 20:
                for j in o:
                    g[j] = bytehash.ranges(bytehash.prefix(data[at[j] : at[j] + shared]), np.zeros(1, np.int64), np.array([shared]))[0]
                continue
            pre = bytehash.prefix(data[here : at[o[-1]] + shared])
            g[o] = bytehash.ranges(pre, at[o] - here, at[o] - here + shared)
        core = [hashlib.blake2b(raw[j : j + shared], digest_size=16).digest() for j in (at - base).tolist()]
        g = bytehash.mix(g + k.astype(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F)).view(np.int64)
        sides = [pa.Array.from_buffers(pa.binary(wide), len(at), [None, pa.py_buffer(np.ascontiguousarray(m))]).cast(pa.binary()) for m in around]
        return pa.RecordBatch.from_arrays([pa.array(g), pa.array(core, pa.binary()), pa.array(k1[row]), pa.array(k2[row]), pa.array(p - k * STEP), pa.array(low.astype(np.int32)), pa.array(high.astype(np.int32)), *sides], _RANGE)

    return texts.mapInArrow(run, "g long, core binary, k1 long, k2 long, last long, low int, high int, left binary, right binary")


_RANGE = ["g", "core", "k1", "k2", "last", "low", "high", "left", "right"]


def _spans(ranges: DataFrame, length: int, crowded: int) -> DataFrame:
    """(k1, k2, first, end): byte ranges of texts that repeated strings cover. Of a core that has more than `crowded` of them, one of equal ranges comes back as it is."""
    wide = STEP - 1

    def flush(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(held).combine_chunks()
        names = np.frombuffer(b"".join(table.column("core").to_pylist()), np.uint64).reshape(-1, 2)
        g = table.column("g").to_numpy()
        fresh = np.ones(len(g), bool)
        fresh[1:] = (g[1:] != g[:-1]) | (names[1:] != names[:-1]).any(1)
        group = np.cumsum(fresh)
        size = np.bincount(group)
        rows = np.flatnonzero(size[group] > 1)
        if not len(rows):
            return
        table = table.take(pa.array(rows))
        left, right = (np.frombuffer(b"".join(table.column(c).to_pylist()), np.uint8).reshape(-1, wide) for c in ("left", "right"))
        low, high = (table.column(c).to_numpy().astype(np.int64) for c in ("low", "high"))
        found = repeated_strings(group[rows], left, right, low, high)
        edge = np.diff(np.pad(found.astype(np.int8), ((0, 0), (1, 1))), axis=1)
        row, a = np.nonzero(edge == 1)
        b = np.nonzero(edge == -1)[1] - 1
        k1, k2, last = (table.column(c).to_numpy()[row] for c in ("k1", "k2", "last"))
        if len(row):
            none = [pa.nulls(len(row), f.type) for f in (table.schema.field(c) for c in _OPEN)]
            yield pa.RecordBatch.from_arrays([pa.array(k1), pa.array(k2), pa.array(last - b), pa.array(last - a + length), *none], ["k1", "k2", "first", "end", *_OPEN])

    def as_they_are(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        """One of equal ranges, for all its strings to be counted; of those that occur again in the batch, also what they cover."""
        keys = [np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint8).reshape(-1, wide) for c in ("left", "right")]
        keys += [batch.column(c).to_numpy()[:, None] for c in ("low", "high")]
        like = np.ones(batch.num_rows + 1, bool)
        like[0] = like[-1] = False
        for k in keys:
            like[1:-1] &= (k[1:] == k[:-1]).all(1)
        one = batch.filter(pa.array(~like[:-1]))
        none = pa.nulls(one.num_rows, pa.int64())
        yield pa.RecordBatch.from_arrays([one.column("k1"), one.column("k2"), none, none, *(one.column(c) for c in _OPEN)], ["k1", "k2", "first", "end", *_OPEN])
        many = batch.filter(pa.array(like[:-1] | like[1:]))
        if many.num_rows:
            last, low, high = (many.column(c).to_numpy() for c in ("last", "low", "high"))
            none = [pa.nulls(many.num_rows, many.schema.field(c).type) for c in _OPEN]
            yield pa.RecordBatch.from_arrays([many.column("k1"), many.column("k2"), pa.array(last - high), pa.array(last - low + length), *none], ["k1", "k2", "first", "end", *_OPEN])

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []  # whole groups, then the one that may go on
        rows, own, of_own, passed = 0, None, 0, None
        for batch in it:
            g, core = batch.column("g").to_numpy(), batch.column("core")
            n = len(g)
            if not n:
                continue
            names = np.frombuffer(b"".join(core.to_pylist()), np.uint64).reshape(-1, 2)
            fresh = np.ones(n, bool)
            fresh[1:] = (g[1:] != g[:-1]) | (names[1:] != names[:-1]).any(1)
            fresh[0] = own != (g[0], core[0].as_py())
            starts = np.flatnonzero(fresh)
            at = 0
            if not fresh[0]:  # the group of the batch before goes on
                at = int(starts[0]) if len(starts) else n
                if passed == own:
                    yield from as_they_are(batch.slice(0, at))
                else:
                    held.append(batch.slice(0, at))
                    rows, of_own = rows + at, of_own + at
            if len(starts):
                if rows >= ROWS:
                    yield from flush(held)
                    held, rows = [], 0
                begin = int(starts[-1])
                if begin > at:
                    held.append(batch.slice(at, begin - at))
                    rows += begin - at
                if rows >= ROWS:
                    yield from flush(held)
                    held, rows = [], 0
                held.append(batch.slice(begin))
                own, of_own = (g[begin], core[begin].as_py()), n - begin
                rows += of_own
            if of_own > crowded and passed != own:
                table = pa.Table.from_batches(held)
                whole = table.num_rows - of_own
                if whole:
                    yield from flush(table.slice(0, whole).to_batches())
                for part in table.slice(whole).to_batches():
                    yield from as_they_are(part)
                held, rows, passed = [], 0, own
        if held:
            yield from flush(held)

    dealt = ranges.repartition("g").sortWithinPartitions("g", "core", "left", "right", "low", "high")
    return dealt.mapInArrow(run, "k1 long, k2 long, first long, end long, core binary, last long, low int, high int, left binary, right binary")


_OPEN = ["core", "last", "low", "high", "left", "right"]


def _one_by_one(ranges: DataFrame, length: int) -> DataFrame:
    """The same for ranges of crowded cores: each string is named by a digest, and names are counted, which needs no group in one task."""
    wide = STEP - 1

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            out = []
            for k1, k2, core, last, low, high, left, right in zip(*(batch.column(c).to_pylist() for c in ("k1", "k2", *_OPEN)), strict=True):
                for n in range(low, high + 1):
                    name = hashlib.blake2b(core + bytes([n]) + left[wide - n :] + right[: wide - n], digest_size=16).digest()
                    out.append((int.from_bytes(name[:8], "little", signed=True), int.from_bytes(name[8:], "little", signed=True), k1, k2, last - n))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], ["w1", "w2", "k1", "k2", "at"])

    each = written(ranges.mapInArrow(run, "w1 long, w2 long, k1 long, k2 long, at long"), "crowded-strings")
    again = each.groupBy("w1", "w2").agg(F.count("*").alias("n")).where("n > 1").select("w1", "w2")
    return each.join(again, ["w1", "w2"]).select("k1", "k2", F.col("at").alias("first"), (F.col("at") + length).alias("end"))


def _cut(texts: DataFrame) -> DataFrame:
    """(k1, k2, n_removed, n_spans, kept): texts (k1, k2, t, spans) without the bytes of their spans."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            removed, count, kept = [], [], []
            for t, spans in zip(batch.column("t").cast(pa.large_binary()).to_pylist(), batch.column("spans"), strict=True):
                first, end = (spans.values.field(c).to_numpy() for c in ("first", "end"))
                order = np.argsort(first, kind="stable")
                first, end = first[order], np.maximum.accumulate(end[order])
                fresh = np.flatnonzero(np.concatenate([[True], first[1:] > end[:-1]]))
                low, high = first[fresh].tolist(), end[np.append(fresh[1:] - 1, len(end) - 1)].tolist()
                removed.append(sum(high) - sum(low))
                count.append(len(low))
                kept.append(b"".join(t[a:b] for a, b in zip([0, *high], [*low, len(t)], strict=True)))
            yield pa.RecordBatch.from_arrays([batch.column("k1"), batch.column("k2"), pa.array(removed, pa.int64()), pa.array(count, pa.int64()), pa.array(kept, pa.binary())], ["k1", "k2", "n_removed", "n_spans", "kept"])

    return texts.mapInArrow(run, "k1 long, k2 long, n_removed long, n_spans long, kept binary")


def _named(docs: DataFrame, text: str, *more: Column) -> DataFrame:
    """docs' texts (null: empty) as t, named by two hashes, 128 bits together."""
    given = docs.select(*more, F.coalesce(F.col(f"`{text}`"), F.lit("")).alias("t"))
    return given.withColumn("k1", F.xxhash64("t")).withColumn("k2", F.xxhash64(F.lit("second"), F.col("t")))


def repeated(docs: DataFrame, text: str = "text", length: int = LENGTH, gram: int = GRAM, hot: int = HOT) -> DataFrame:
    """(k1, k2, n_removed, n_spans, kept) for distinct texts that lose bytes; k1 and k2 name a text, see _named().

    A byte is removed if a string of `length` bytes over it also starts anywhere else, in another text or in
    the same one; overlaps count. A text that occurs again, as a whole, loses all if it has `length` bytes;
    that is left to the caller. Strings never reach over two texts. Null and short texts lose nothing. Columns other than the text are not read.
    """
    given = _named(small_batches(docs), text)
    found = written(_anchor_rows(given, length, gram), "anchors")
    ends = [f(c).alias(f"{f.__name__}_{c}") for c in ("k1", "k2", "pos") for f in (F.min, F.max)]
    again = found.groupBy("hash").agg(*ends).where("min_k1 <> max_k1 or min_k2 <> max_k2 or min_pos <> max_pos").select("hash")
    places = found.join(again, "hash").groupBy("k1", "k2").agg(F.collect_set(F.struct("pos", "low", "high")).alias("places"))
    places = written(places, "anchor-places")
    once = masked(given, F.col("k1"), mask_of(places, F.col("k1")))[0].groupBy("k1", "k2").agg(F.first("t").alias("t"))
    texts = written(once.join(places, ["k1", "k2"]), "anchor-texts")
    spans = written(_spans(_ranges(texts.select("k1", "k2", F.col("t").cast("binary").alias("t"), "places"), length), length, hot), "spans")
    rest = _one_by_one(spans.where("first is null").drop("first", "end"), length)
    spans = spans.where("first is not null").select("k1", "k2", "first", "end").unionByName(rest)
    return _cut(texts.select("k1", "k2", "t").join(spans.groupBy("k1", "k2").agg(F.collect_set(F.struct("first", "end")).alias("spans")), ["k1", "k2"]))


def without_repeats(docs: DataFrame, id_col: str = "doc_id", text: str = "text", length: int = LENGTH, gram: int = GRAM, hot: int = HOT, rest: bool = False) -> DataFrame:
    """Per row of docs: id, n_bytes, n_removed, n_spans, kept_sha256 of the bytes that stay; with `rest` also these as `text` (a sign that was cut through is replaced). See repeated()."""
    cut = repeated(docs, text, length, gram, hot)
    light = _named(docs, text, F.col(f"`{id_col}`").cast("long").alias("id")).withColumn("n_bytes", F.octet_length("t").cast("long"))
    copied = light.groupBy("k1", "k2", "n_bytes").agg(F.count("*").alias("n")).where((F.col("n") > 1) & (F.col("n_bytes") >= length)).select("k1", "k2", F.lit(True).alias("copied"))
    verdict = written(cut.join(copied, ["k1", "k2"], "full"), "repeat-verdicts")
    met, calm = masked(light, F.col("k1"), mask_of(verdict, F.col("k1")))
    whole = calm.select("id", "n_bytes", F.lit(0).cast("long").alias("n_removed"), F.lit(0).cast("long").alias("n_spans"), F.col("t").cast("binary").alias("kept"))
    gone = F.coalesce("copied", F.lit(False))
    kept = F.when(gone, F.lit(b"")).otherwise(F.coalesce("kept", F.col("t").cast("binary")))
    lost = F.when(gone, F.col("n_bytes")).otherwise(F.coalesce("n_removed", F.lit(0).cast("long")))
    runs = F.when(gone, F.lit(1).cast("long")).otherwise(F.coalesce("n_spans", F.lit(0).cast("long")))
    told = met.join(verdict, ["k1", "k2"], "left").select("id", "n_bytes", lost.alias("n_removed"), runs.alias("n_spans"), kept.alias("kept"))
    stays = [F.make_valid_utf8(F.col("kept").cast("string")).alias("text")] if rest else []
    return whole.unionByName(told).select(F.col("id").alias(id_col), "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"), *stays)
