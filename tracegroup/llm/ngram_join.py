"""Exact Jaccard join of texts on word shingles, bounded by count vectors in an R-tree.

Shingles are hashed into groups; a text's counts per group are a point, and the sum of coordinate
minima bounds how many shingles two texts share. Texts meet only where their rarest quarter of
shingles meets, which no pair of the wanted similarity can avoid. What the bounds leave is verified
on whole shingle sets. Texts are first gathered into components by stars around a few of them, so
that only pairs across components have to be looked for, and those are named as a text beside a
component, never as all pairs with its members.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tracegroup.llm import bytehash
from tracegroup.llm.common import bytes_of, components, mask_of, masked, slices, small_batches, written

GROUPS = 256
#: Texts per leaf of the tree.
LEAF = 64
#: Entries of the list of frequent shingles. It only orders shingles, so no result depends on it.
FREQUENT = 100_000
WORDS = 5
#: Ranges of hashes whose smallest values propose stars, and how many of them make one proposal.
RANGES, JOINED = 32, 4
#: Nodes of a block that one task takes; a larger block is dealt out as pairs of parts of this size.
BLOCK = 16_384
#: Shingles of a component's members that a text is held against in one task, and texts that one task holds against them.
MEMBERS, QUERIES = 100_000, 2_048
#: Similarity: 100 * shared >= PERCENT * united.
PERCENT = 75


def sets_of(column: pa.Array, n: int = WORDS) -> Iterator[tuple[int, int, list[np.ndarray]]]:
    """Row ranges with each row's distinct shingle hashes, sorted. A-Z count as lower case; null as empty."""
    data, offsets = bytes_of(column)
    for a, b in slices(offsets):
        part, off = bytehash.LOWER[data[offsets[a] : offsets[b]]], offsets[a : b + 1] - offsets[a]
        start, end, row = bytehash.spans(part, off, bytehash.WORD.view(np.uint8))
        words = bytehash.token_hashes(part, start, end)
        cut = np.searchsorted(row, np.arange(b - a + 1))
        yield a, b, [np.unique(bytehash.shingles(words[i:j], n)) for i, j in zip(cut[:-1], cut[1:], strict=True)]


def counts(shingles: np.ndarray) -> bytes:
    """The point of a text: how many of its shingles fall into each group, a byte each where that is enough."""
    found = np.bincount((shingles >> np.uint64(56)).astype(np.int64), minlength=GROUPS)
    return found.astype(np.uint8 if found.max() < 256 else np.int32).tobytes()


def points_of(column: pa.ChunkedArray | pa.Array) -> np.ndarray:
    """Points, one row each."""
    raw = column.to_pylist()
    if all(len(x) == GROUPS for x in raw):
        return np.frombuffer(b"".join(raw), np.uint8).reshape(-1, GROUPS)
    return np.stack([np.frombuffer(x, np.uint8 if len(x) == GROUPS else np.int32).astype(np.int32) for x in raw])


def overlap(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Sum of coordinate minima: at least as many shingles as two texts (or boxes) share."""
    return np.minimum(x, y).sum(-1, dtype=np.int64)


_EDGES = (np.arange(RANGES, dtype=np.uint64) << np.uint64(64 - RANGES.bit_length() + 1)).astype(np.uint64)
_ODD = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5][:JOINED], np.uint64)


def proposals(shingles: np.ndarray) -> np.ndarray:
    """Names that similar sets are likely to have in common: hashes of the first values from some places on, a few at a time."""
    first = shingles[np.searchsorted(shingles, _EDGES) % len(shingles)].reshape(-1, JOINED)
    return bytehash.mix((first * _ODD).sum(1, dtype=np.uint64) + np.arange(len(first), dtype=np.uint64)).view(np.int64)


def node_of(shingles: np.ndarray) -> int:
    """One signed 64-bit name for a shingle set; texts with equal sets are one node."""
    return int.from_bytes(hashlib.blake2b(shingles.tobytes(), digest_size=8).digest(), "little", signed=True)


def prefix_size(n: int) -> int:
    """How many of n ordered shingles must be looked at: a partner shares at least PERCENT % of them."""
    return n - (-(-PERCENT * n // 100)) + 1


def linked(shared: int, a: int, b: int) -> bool:
    return 100 * shared >= PERCENT * (a + b - shared) and a > 0 and b > 0


class CountTree:
    """R-tree of points: each node has the largest count per group, the range of sizes and the range of components below it.

    A component with more points than a leaf holds is a branch of its own, which is never held against itself.
    """

    def __init__(self, points: np.ndarray, sizes: np.ndarray, parts: np.ndarray):
        self.points, self.sizes, self.parts = points, sizes, parts
        self.root = self._load(np.arange(len(points)))

    def _load(self, rows: np.ndarray) -> tuple:
        top, size, part = self.points[rows].max(0), self.sizes[rows], self.parts[rows]
        box = (top, int(size.min()), int(size.max()), part.min(), part.max())
        if len(rows) <= LEAF:
            return (*box, rows, ())
        if box[3] != box[4]:
            own, back, times = np.unique(part, return_inverse=True, return_counts=True)
            if times.max() > LEAF:
                most = back == times.argmax()
                return (*box, rows, (self._load(rows[most]), self._load(rows[~most])))
        low = self.points[rows].min(0)
        spread = top.astype(np.int64) - low
        by_size = box[2] - box[1] > spread.max()
        order = np.argsort(size if by_size else self.points[rows, spread.argmax()], kind="stable")
        halves = np.array_split(rows[order], 2)
        return (*box, rows, tuple(self._load(h) for h in halves))

    @staticmethod
    def _apart(x: tuple, y: tuple) -> bool:
        """Whether no pair between two nodes can be wanted: one component, sizes too far apart, or too small a bound."""
        if x[3] == x[4] == y[3] == y[4]:
            return True
        if 100 * x[2] < PERCENT * y[1] or 100 * y[2] < PERCENT * x[1]:
            return True
        return bool((100 + PERCENT) * overlap(x[0], y[0]) < PERCENT * (x[1] + y[1]))

    def pairs(self) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Row pairs of different components that the bounds leave."""
        todo = [(self.root, self.root)]
        while todo:
            x, y = todo.pop()
            if self._apart(x, y):
                continue
            if not x[6] and not y[6]:
                a, b = x[5], y[5]
                fits = self.parts[a][:, None] != self.parts[b][None, :]
                if x is y:
                    fits = np.triu(fits, 1)
                na, nb = self.sizes[a][:, None], self.sizes[b][None, :]
                fits &= (100 * na >= PERCENT * nb) & (100 * nb >= PERCENT * na)
                i, j = np.nonzero(fits)
                i, j = a[i], b[j]
                ok = (100 + PERCENT) * overlap(self.points[i], self.points[j]) >= PERCENT * (self.sizes[i] + self.sizes[j])
                if ok.any():
                    yield i[ok], j[ok]
            elif x is y:
                todo += [(p, q) for k, p in enumerate(x[6]) for q in x[6][k:]]
            else:
                todo += [(p, q) for p in x[6] or (x,) for q in y[6] or (y,)]


def _profile(docs: DataFrame, id_col: str, text: str) -> DataFrame:
    """Rows of kind 0: id, tk (hash of the text), node, n, point and proposals; of kind 1: shingles that several texts of a slice share, with their number there."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            for a, b, sets in sets_of(batch.column("t")):
                node = [node_of(s) if len(s) else None for s in sets]
                told = [pa.array(np.zeros(b - a, np.int32)), batch.column("id").slice(a, b - a), batch.column("tk").slice(a, b - a), pa.array(node, pa.int64()), pa.array([len(s) for s in sets], pa.int64())]
                told += [pa.array([counts(s) if len(s) else None for s in sets], pa.binary()), pa.array([proposals(s) if len(s) else None for s in sets], pa.list_(pa.int64()))]
                yield pa.RecordBatch.from_arrays(told, names)
                once = {k: s for k, s in zip(node, sets, strict=True)}
                shingle, times = np.unique(np.concatenate(list(once.values())), return_counts=True)
                shingle, times = shingle[times > 2], times[times > 2]
                if len(shingle):
                    none = pa.nulls(len(shingle), pa.int64())
                    yield pa.RecordBatch.from_arrays([pa.array(np.ones(len(shingle), np.int32)), none, none, pa.array(shingle.view(np.int64)), pa.array(times.astype(np.int64)), pa.nulls(len(shingle), pa.binary()), pa.nulls(len(shingle), pa.list_(pa.int64()))], names)

    names = ["kind", "id", "tk", "node", "n", "point", "proposals"]
    given = docs.select(F.col(f"`{id_col}`").cast("long").alias("id"), F.xxhash64(F.coalesce(F.col(f"`{text}`"), F.lit(""))).alias("tk"), F.col(f"`{text}`").alias("t"))
    return given.mapInArrow(run, "kind int, id long, tk long, node long, n long, point binary, proposals array<long>")


def _frequent(profile: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Shingles that many texts share, sorted, and how many: a list of bounded length."""
    often = profile.where("kind = 1").groupBy("node").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "node").limit(FREQUENT).toArrow()
    keys, rank = often.column("node").to_numpy().view(np.uint64), often.column("n").to_numpy()
    order = np.argsort(keys)
    return keys[order], rank[order]


def _postings(docs: DataFrame, text: str, frequent: tuple[np.ndarray, np.ndarray]) -> DataFrame:
    """(shingle, node) for the rarest shingles of every text. A task leaves out most texts whose set it has met."""
    shared = docs.sparkSession.sparkContext.broadcast(frequent)

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, rank = shared.value
        met = np.zeros(1 << 16, np.int64)  # the last node of each slot
        for batch in it:
            for _, _, sets in sets_of(batch.column("t")):
                out, names = [], []
                for s in sets:
                    if not len(s) or met[(node := node_of(s)) & 0xFFFF] == node:
                        continue
                    met[node & 0xFFFF] = node
                    p = prefix_size(len(s))
                    if len(keys):
                        at = np.minimum(np.searchsorted(keys, s), len(keys) - 1)
                        often = np.where(keys[at] == s, rank[at], 0)
                        if often.any():
                            s = s[np.lexsort((s, often))]
                    out.append(s[:p])
                    names.append(node)
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(out).view(np.int64)), pa.array(np.repeat(np.array(names, np.int64), [len(x) for x in out]))], ["shingle", "node"])

    return docs.select(F.col(f"`{text}`").alias("t")).mapInArrow(run, "shingle long, node long")


def _blocks(postings: DataFrame) -> DataFrame:
    """(shingle, node), each once, for shingles that several nodes have. Streams over sorted rows; of a block only its first node is remembered."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last_key = last_node = leader = None
        told = False  # whether the block that goes on has its first node written
        for batch in it:
            key, node = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            if not len(key):
                continue
            fresh = np.ones(len(key), bool)
            fresh[1:] = key[1:] != key[:-1]
            fresh[0] = last_key is None or key[0] != last_key
            other = np.ones(len(key), bool)
            other[1:] = fresh[1:] | (node[1:] != node[:-1])
            other[0] = fresh[0] or node[0] != last_node
            begin = np.maximum.accumulate(np.where(fresh, np.arange(len(key)), -1))
            lead = np.where(begin < 0, leader if leader is not None else 0, node[np.maximum(begin, 0)])
            rows = np.flatnonzero(other & ~fresh)
            second = np.ones(len(rows), bool)
            second[1:] = begin[rows[1:]] != begin[rows[:-1]]
            if len(rows) and begin[rows[0]] < 0:
                second[0] = not told
            ended = begin[-1]
            told = bool(len(rows) and begin[rows[-1]] == ended) or (ended < 0 and told)
            last_key, last_node, leader = key[-1], node[-1], lead[-1]
            if len(rows):
                first = rows[second]
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([key[rows], key[first]])), pa.array(np.concatenate([node[rows], lead[first]]))], ["shingle", "node"])

    dealt = postings.repartition("shingle").sortWithinPartitions("shingle", "node")
    return dealt.mapInArrow(run, "shingle long, node long")


def _enough(common: Column, na: Column, nb: Column) -> Column:
    """Whether two sets with so many common shingles among their rarest can be similar enough.

    Of the two, take the one whose rarest shingles end first: all that it shares there is counted, and
    beyond it has no more than its other shingles to share. Which one that is need not be known, as the
    larger rest is allowed for.
    """
    rest = F.greatest(F.ceil(na * PERCENT / 100), F.ceil(nb * PERCENT / 100)) - 1
    return (100 + PERCENT) * (common + rest) >= PERCENT * (na + nb)


def _bounded(pairs: DataFrame) -> DataFrame:
    """Pairs (a, b, na, nb, pa, pb) that sizes and summed coordinate minima leave, as (a, b)."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            na, nb = batch.column("na").to_numpy(), batch.column("nb").to_numpy()
            ok = (100 * na >= PERCENT * nb) & (100 * nb >= PERCENT * na)
            if len(ok):
                ok &= (100 + PERCENT) * overlap(points_of(batch.column("pa")), points_of(batch.column("pb"))) >= PERCENT * (na + nb)
            yield batch.filter(pa.array(ok)).select(["a", "b"])

    return pairs.mapInArrow(run, "a long, b long")


class SetIndex:
    """Shingle sets by shingle, to count what another set shares with each of them."""

    def __init__(self, sets: list[np.ndarray]):
        self.sizes = np.array([len(s) for s in sets], np.int64)
        values = np.concatenate(sets)
        order = np.argsort(values, kind="stable")
        self.owner = np.repeat(np.arange(len(sets)), self.sizes)[order]
        self.keys, self.start = np.unique(values[order], return_index=True)
        self.count = np.diff(np.append(self.start, len(values)))

    def linked(self, s: np.ndarray) -> np.ndarray:
        """The sets that are similar enough to s."""
        at = np.minimum(np.searchsorted(self.keys, s), len(self.keys) - 1)
        at = at[self.keys[at] == s]
        start, count = self.start[at], self.count[at]
        places = np.repeat(start - np.cumsum(count) + count, count) + np.arange(count.sum())
        shared = np.bincount(self.owner[places], minlength=len(self.sizes))
        return np.flatnonzero((100 * shared >= PERCENT * (self.sizes + len(s) - shared)) & (shared > 0))


def _verified(base: DataFrame, queries: DataFrame, texts: DataFrame) -> DataFrame:
    """(a, b): for each query b of a group, one of the group's base nodes a whose whole shingle set is similar enough, if there is one.

    base, queries: (g, salt, node). A task has the base of a group in memory, which the caller keeps small, and streams the queries.
    """
    kinds = base.select("g", "salt", F.lit(0).alias("kind"), "node").unionByName(queries.select("g", "salt", F.lit(1).alias("kind"), "node"))

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, held, names, index = None, [], [], None
        for batch in it:
            g, salt, kind, node = (batch.column(c).to_numpy() for c in ("g", "salt", "kind", "node"))
            x, y = [], []
            for i, _, sets in sets_of(batch.column("t")):
                for k, s in enumerate(sets, i):
                    if own != (g[k], salt[k]):
                        own, held, names, index = (g[k], salt[k]), [], [], None
                    if kind[k] == 0:
                        held.append(s)
                        names.append(node[k])
                        continue
                    if held and index is None:
                        index = SetIndex(held)
                    hits = index.linked(s) if index is not None else ()
                    hit = next((h for h in hits if names[h] != node[k]), None)
                    if hit is not None:
                        x.append(names[hit])
                        y.append(node[k])
            if x:
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()), pa.array(y, pa.int64())], ["a", "b"])

    dealt = kinds.join(texts, "node").select("g", "salt", "kind", "node", "t").repartition("g", "salt").sortWithinPartitions("g", "salt", "kind")
    return dealt.mapInArrow(run, "a long, b long")


def _cross(members: DataFrame) -> DataFrame:
    """(a, na, q, common, low, high): node a beside component q, with the blocks they share and the sizes of q's nodes there that the tree's bounds leave.

    members: block, node, part (component so far), psize, n, point. Of two components the nodes of the one with
    fewer nodes are named, so that the same way holds in all blocks. Whether the bounds leave a pair
    does not depend on the block, so every shared block counts.
    """

    def told(i: np.ndarray, j: np.ndarray, cut: np.ndarray, node, part, psize, n) -> Iterator[pa.RecordBatch]:
        swap = (psize[i] > psize[j]) | ((psize[i] == psize[j]) & (part[i] > part[j]))
        i, j = np.where(swap, j, i), np.where(swap, i, j)
        block = np.searchsorted(cut, i, "right")
        once = pa.table({"g": block, "a": node[i], "na": n[i], "q": part[j], "nb": n[j]}).group_by(["g", "a", "na", "q"]).aggregate([("nb", "min"), ("nb", "max")])
        found = once.group_by(["a", "na", "q"]).aggregate([([], "count_all"), ("nb_min", "min"), ("nb_max", "max")])
        for batch in found.combine_chunks().to_batches():
            yield pa.RecordBatch.from_arrays([batch.column(c) for c in ("a", "na", "q", "count_all", "nb_min_min", "nb_max_max")], ["a", "na", "q", "common", "low", "high"])

    def flush(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(held).combine_chunks()
        key, node, part, psize, n = (table.column(c).to_numpy() for c in ("block", "node", "part", "psize", "n"))
        cut = np.concatenate([[0], np.flatnonzero(key[1:] != key[:-1]) + 1, [len(key)]])
        size = np.diff(cut)
        mixed = np.minimum.reduceat(part, cut[:-1]) != np.maximum.reduceat(part, cut[:-1])
        if not mixed.any():
            return
        points = points_of(table.column("point"))
        first = cut[:-1][mixed & (size == 2)]  # blocks of two are bounded all at once
        sizes = n[first] + n[first + 1]
        fits = (100 + PERCENT) * overlap(points[first], points[first + 1]) >= PERCENT * sizes
        fits &= (100 * n[first] >= PERCENT * n[first + 1]) & (100 * n[first + 1] >= PERCENT * n[first])
        x, y, held_pairs = [first[fits]], [first[fits] + 1], int(fits.sum())
        for g in np.flatnonzero(mixed & (size > 2)):
            rows = slice(cut[g], cut[g + 1])
            for i, j in CountTree(points[rows], n[rows], part[rows]).pairs():
                x.append(i + cut[g])
                y.append(j + cut[g])
                held_pairs += len(i)
                if held_pairs > 500_000:  # a block told in two goes counts twice, which only leaves more to verify
                    yield from told(np.concatenate(x), np.concatenate(y), cut, node, part, psize, n)
                    x, y, held_pairs = [], [], 0
        if held_pairs:
            yield from told(np.concatenate(x), np.concatenate(y), cut, node, part, psize, n)

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        rows = 0
        for batch in it:
            if not batch.num_rows:
                continue
            key = batch.column("block").to_numpy()
            cut = int(np.searchsorted(key, key[-1]))  # where the last, perhaps unfinished, block begins
            if cut or (held and key[0] != held[-1].column("block")[-1].as_py()):
                if cut:
                    held.append(batch.slice(0, cut))
                    rows += cut
                if rows >= BLOCK:
                    yield from flush(held)
                    held, rows = [], 0
                batch = batch.slice(cut)
            held.append(batch)
            rows += batch.num_rows
        if held:
            yield from flush(held)

    dealt = members.repartition("block").sortWithinPartitions("block")
    return dealt.mapInArrow(run, "a long, na long, q long, common long, low long, high long")


def _stars(nodes: DataFrame) -> DataFrame:
    """(a, b): node b beside a leader a of a proposal that both have, where sizes and points let them be similar. Two leaders a proposal."""
    rows = nodes.select("node", F.explode("proposals").alias("proposal"))
    other = F.min(F.struct(F.xxhash64("node").alias("h"), F.col("node").alias("a")))["a"]
    heads = rows.groupBy("proposal").agg(F.min("node").alias("x"), F.max("node").alias("most"), other.alias("y")).where("x != most")
    met = rows.join(heads, "proposal").select("node", F.explode(F.array_distinct(F.array("x", "y"))).alias("a")).where("a != node")
    met = met.select("a", F.col("node").alias("b")).distinct()
    sides = nodes.select("node", "n", "point")
    return _bounded(met.join(sides.toDF("a", "na", "pa"), "a").join(sides.toDF("b", "nb", "pb"), "b"))


def similar_groups(docs: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """Per row of docs: id, n_shingles, component_id, class (one for all rows of a component, null without words) and tk, a hash of the text.

    Words are runs of bytes other than white space, A-Z lower-cased; a text's set has its distinct runs of
    five words, or the whole sequence if it is shorter. Rows link when 100 * shared >= 75 * united; a
    component is all rows that links reach, named by its smallest id. A text without words is its own
    component. Null texts count as empty; a null id is never a component's name unless all are null.
    Repeated rows and texts with equal sets are one node; rows stay. Empty tables give empty results.

    Plan. First each node is held against a few leaders that it shares a proposal with; what links is
    gathered into components. Then nodes meet at their rarest shingles (about a quarter of each set, by an order that
    puts frequent ones last), which no linked pair can avoid. Blocks of one component are left out there; in the others
    the R-tree's bounds say which nodes may link with which other components, and a node that shares
    enough of its rarest shingles with a component is held against its members, dealt out in chunks.
    So neither groups of near copies nor those that just miss the threshold are ever written as pairs.
    """
    profile = written(_profile(small_batches(docs), id_col, text), "shingle-profile")
    rows = profile.where("kind = 0").drop("kind")
    nodes = rows.where("node is not null").groupBy("node").agg(F.min("id").alias("low"), F.min("tk").alias("tk"), F.first("n").alias("n"), F.first("point").alias("point"), F.first("proposals").alias("proposals"))
    nodes = written(nodes, "shingle-nodes")

    stars = written(_stars(nodes), "star-pairs")
    per = stars.groupBy("a").agg(F.ceil(F.count("*") / QUERIES).cast("int").alias("deal"))
    queries = stars.join(per, "a").select(F.col("a").alias("g"), F.pmod(F.xxhash64("b"), F.col("deal")).cast("int").alias("salt"), F.col("b").alias("node"))
    base = per.select(F.col("a").alias("g"), F.explode(F.expr("sequence(0, deal - 1)")).alias("salt"), F.col("a").alias("node"))
    links = written(_verified(base, queries, _texts(docs, text, nodes, base, queries)), "star-links")
    parts = written(components(links), "star-parts")

    members = written(_blocks(_postings(docs, text, _frequent(profile))), "shingle-blocks")
    size = parts.groupBy("component").agg(F.count("*").alias("psize"))
    sides = nodes.select("node", "n", "point").join(parts.join(size, "component"), "node", "left")
    sides = written(sides.select("node", "n", "point", F.coalesce("component", "node").alias("part"), F.coalesce("psize", F.lit(1)).alias("psize")), "shingle-sides")
    mixed = members.join(sides.select("node", "part"), "node").groupBy("shingle").agg(F.min("part").alias("low"), F.max("part").alias("high"), F.count("*").alias("m"))
    mixed = mixed.where("low != high").select("shingle", F.ceil(F.col("m") / BLOCK).cast("int").alias("deal"))
    own = F.pmod(F.xxhash64("node"), F.col("deal")).cast("int")
    met = members.join(mixed, "shingle").select("shingle", "node", "deal", own.alias("own"), F.explode(F.expr("sequence(0, deal - 1)")).alias("other"))
    block = F.when(F.col("deal") == 1, F.col("shingle")).otherwise(F.xxhash64("shingle", F.least("own", "other"), F.greatest("own", "other")))
    met = met.select(block.alias("block"), "node").join(sides, "node")
    beside = written(_cross(met), "cross-blocks").groupBy("a", "na", "q").agg(F.sum("common").alias("common"), F.min("low").alias("low"), F.max("high").alias("high"))
    # what is asked of the shared shingles falls with the distance between the sizes, so the ends of the range decide
    beside = written(beside.where(_enough(F.col("common"), F.col("na"), F.col("low")) | _enough(F.col("common"), F.col("na"), F.col("high"))).select("a", "q"), "cross-beside")

    inside = sides.select(F.col("part").alias("q"), "node", "n").join(beside.groupBy("q").agg(F.ceil(F.count("*") / QUERIES).cast("int").alias("salts")), "q")
    chunks = inside.groupBy("q").agg(F.ceil(F.sum("n") / MEMBERS).cast("int").alias("chunks"), F.first("salts").alias("salts"))
    chunks = written(chunks, "cross-chunks")
    group = F.xxhash64("q", "chunk").alias("g")
    base = inside.drop("salts").join(chunks, "q").withColumn("chunk", F.pmod(F.xxhash64("node"), F.col("chunks")).cast("int")).select(group, F.explode(F.expr("sequence(0, salts - 1)")).alias("salt"), "node")
    queries = beside.join(chunks, "q").select("q", F.col("a").alias("node"), F.pmod(F.xxhash64("a"), F.col("salts")).cast("int").alias("salt"), F.explode(F.expr("sequence(0, chunks - 1)")).alias("chunk")).select(group, "salt", "node")
    more = written(_verified(base, queries, _texts(docs, text, nodes, base, queries)), "cross-links")
    if not more.isEmpty():
        parts = components(more.unionByName(parts.select(F.col("component").alias("a"), F.col("node").alias("b"))))
    named = nodes.select("node", "low").join(parts, "node", "left").select("node", "low", F.coalesce("component", "node").alias("class"))
    lowest = named.groupBy("class").agg(F.min("low").alias("component_id"))
    names = named.join(lowest, "class").select("node", "class", "component_id")
    told = rows.join(names, "node", "left").withColumn("component_id", F.when(F.col("node").isNull(), F.col("id")).otherwise(F.col("component_id")))
    return told.select(F.col("id").alias(id_col), F.col("n").alias("n_shingles"), "component_id", "class", "tk")


def _texts(docs: DataFrame, text: str, nodes: DataFrame, *asked: DataFrame) -> DataFrame:
    """(node, t): one text for every node asked for. A mask of bounded size keeps other texts from being shuffled."""
    named = asked[0].select("node")
    for more in asked[1:]:
        named = named.unionByName(more.select("node"))
    wanted = written(named.distinct().join(nodes.select("node", "tk"), "node"), "shingle-wanted")
    given = docs.select(F.coalesce(F.col(f"`{text}`"), F.lit("")).alias("t")).withColumn("tk", F.xxhash64("t"))
    found = masked(given, F.col("tk"), mask_of(wanted, F.col("tk")))[0].groupBy("tk").agg(F.first("t").alias("t"))
    return written(wanted.join(found, "tk").select("node", "t"), "shingle-texts")


def keep_one(docs: DataFrame) -> DataFrame:
    """docs with one row of each component: that of the smallest doc_id (a null one counts as largest); of equal rows, one. Columns as given.

    Rows are told apart by id and text. Those that surely have no link and no equal row are passed on where
    they are read; only others are shuffled.
    """
    groups = written(similar_groups(docs).where("class is not null"), "near-groups")
    key = F.struct(F.col("doc_id").isNull().alias("none"), F.col("doc_id").alias("id"), F.col("tk").alias("tk"))
    size = groups.groupBy("class").agg(F.count("*").alias("n"), F.min(key).alias("keep")).where("n > 1")
    crowded = groups.join(size, "class").select("doc_id", "tk", (key == F.col("keep")).alias("stays"))
    touched = written(crowded.groupBy("doc_id", "tk").agg(F.max("stays").alias("stays")), "near-touched")
    tk = F.xxhash64(F.coalesce(F.col("text"), F.lit("")))
    near, calm = masked(docs, F.xxhash64(F.col("doc_id"), tk), mask_of(touched, F.xxhash64("doc_id", "tk")))
    d = near.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("given"), F.col("doc_id").alias("own"), tk.alias("own_tk"))
    met = d.join(touched, d["own"].eqNullSafe(touched["doc_id"]) & (d["own_tk"] == touched["tk"]), "left").where("stays is null or stays").select("given", "own", "own_tk", "stays")
    single = met.where("stays is null").select("given.*")
    repeated = met.where("stays").dropDuplicates(["own", "own_tk"]).select("given.*")
    return calm.unionByName(single).unionByName(repeated)
