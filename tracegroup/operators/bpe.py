"""Byte-pair tokens of identifier pieces: training on piece counts, encoding of distinct pieces."""

from __future__ import annotations

import heapq
from collections import Counter, defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

PAD, UNKNOWN, END = 0, 1, "▁"


@dataclass
class Bpe:
    """Merges in rank order and the vocabulary; ids 0 and 1 are padding and unknown."""

    merges: list[tuple[str, str]]
    vocab: dict[str, int]
    ranks: dict[tuple[str, str], int] = field(init=False)

    def __post_init__(self) -> None:
        self.ranks = {m: i for i, m in enumerate(self.merges)}

    def symbols(self, piece: str) -> list[str]:
        """The piece's tokens: merges applied in rank order. Joined, without the end mark, they give the piece back."""
        now = [*piece, END]
        while len(now) > 1:
            best = min(zip(now, now[1:], strict=False), key=lambda p: self.ranks.get(p, 1 << 60))
            if best not in self.ranks:
                break
            out, i = [], 0
            while i < len(now):
                if i + 1 < len(now) and (now[i], now[i + 1]) == best:
                    out.append(now[i] + now[i + 1])
                    i += 2
                else:
                    out.append(now[i])
                    i += 1
            now = out
        return now

    def encode(self, piece: str) -> list[int]:
        return [self.vocab.get(s, UNKNOWN) for s in self.symbols(piece)]


def piece_counts(frames_pieces: DataFrame) -> DataFrame:
    """(piece, n) of a frame of arrays `pieces`."""
    return frames_pieces.select(F.explode("pieces").alias("piece")).groupBy("piece").agg(F.count("*").alias("n"))


def first_pairs(counts: DataFrame) -> DataFrame:
    """(left, right, n): how often two signs follow each other in all pieces, before any merge."""
    signs = counts.select("n", F.split(F.concat("piece", F.lit(END)), "").alias("s"))
    pairs = signs.select("n", F.explode(F.arrays_zip(F.expr("slice(s, 1, size(s) - 1)").alias("l"), F.expr("slice(s, 2, size(s) - 1)").alias("r"))).alias("p"))
    return pairs.groupBy(F.col("p.l").alias("left"), F.col("p.r").alias("right")).agg(F.sum("n").alias("n"))


def learn(counts: dict[str, int], vocab_size: int = 10_000, min_pair: int = 2) -> Bpe:
    """Merge the most frequent neighbours until the vocabulary is full or no pair occurs min_pair times.

    A pair's count only changes in pieces that have it, so a merge looks at those alone; the heap holds
    outdated entries, which are skipped. Ties go to the smallest pair.
    """
    words = [[*p, END] for p in counts]
    times = list(counts.values())
    pair_n: Counter = Counter()
    where: dict[tuple[str, str], set[int]] = defaultdict(set)
    for w, (word, n) in enumerate(zip(words, times, strict=True)):
        for p in zip(word, word[1:], strict=False):
            pair_n[p] += n
            where[p].add(w)
    signs = sorted({s for w in words for s in w})
    merges: list[tuple[str, str]] = []
    heap = [(-n, p) for p, n in pair_n.items()]
    heapq.heapify(heap)
    while heap and len(merges) + len(signs) + 2 < vocab_size:
        n, pair = heapq.heappop(heap)
        if -n != pair_n.get(pair, 0):
            continue
        if -n < min_pair:
            break
        merges.append(pair)
        changed = set()
        for w in list(where[pair]):
            old, word = words[w], []
            i = 0
            while i < len(old):
                if i + 1 < len(old) and (old[i], old[i + 1]) == pair:
                    word.append(old[i] + old[i + 1])
                    i += 2
                else:
                    word.append(old[i])
                    i += 1
            for p in zip(old, old[1:], strict=False):
                pair_n[p] -= times[w]
                where[p].discard(w)
                changed.add(p)
            for p in zip(word, word[1:], strict=False):
                pair_n[p] += times[w]
                where[p].add(w)
                changed.add(p)
            words[w] = word
        for p in changed:
            if pair_n[p] > 0:
                heapq.heappush(heap, (-pair_n[p], p))
            else:
                pair_n.pop(p, None)
    names = [*signs, *dict.fromkeys(a + b for a, b in merges)]
    return Bpe(merges, {s: i + 2 for i, s in enumerate(dict.fromkeys(names))})


def train(counts: DataFrame, vocab_size: int = 10_000, min_pair: int = 2, most_pieces: int = 2_000_000) -> Bpe:
    """Learn on the driver from the most frequent pieces, most_pieces of them at most; see rounds() beyond that."""
    rows = counts.orderBy(F.desc("n"), "piece").limit(most_pieces).collect()
    return learn({r["piece"]: r["n"] for r in rows}, vocab_size, min_pair)


def rounds(counts: DataFrame, vocab_size: int = 10_000, min_pair: int = 2, per_round: int = 64, most_rounds: int = 400) -> Bpe:
    """Learn on the tasks: each pass counts neighbours, merges the best pairs that share no sign, and counts again.

    Only pairs, not pieces, come to the driver, per_round of them. With per_round = 1 the merges are those of
    learn(); with more, their order may differ.
    """
    from tracegroup.sources.storage import written

    now = written(counts.select("n", F.split(F.concat("piece", F.lit(END)), "").alias("s")), "bpe-pieces")
    signs = sorted(r[0] for r in now.select(F.explode("s")).distinct().collect() if r[0])
    merges: list[tuple[str, str]] = []
    for _ in range(most_rounds):
        room = vocab_size - 2 - len(signs) - len(merges)
        pairs = now.where("size(s) > 1").select("n", F.explode(F.arrays_zip(F.expr("slice(s, 1, size(s) - 1)").alias("l"), F.expr("slice(s, 2, size(s) - 1)").alias("r"))).alias("p"))
        best = pairs.groupBy(F.col("p.l").alias("l"), F.col("p.r").alias("r")).agg(F.sum("n").alias("n")).where(F.col("n") >= min_pair).orderBy(F.desc("n"), "l", "r").limit(per_round).collect()
        chosen, used = [], set()
        for r in best:
            if len(chosen) < room and r["l"] not in used and r["r"] not in used:
                chosen.append((r["l"], r["r"]))
                used |= {r["l"], r["r"]}
        if not chosen:
            break
        merges += chosen
        step = set(chosen)

        @F.udf("array<string>")
        def merged(s: list[str]) -> list[str]:
            out, i = [], 0
            while i < len(s):
                if i + 1 < len(s) and (s[i], s[i + 1]) in step:
                    out.append(s[i] + s[i + 1])
                    i += 2
                else:
                    out.append(s[i])
                    i += 1
            return out

        now = written(now.select("n", merged("s").alias("s")), "bpe-pieces")
    names = [*signs, *(a + b for a, b in merges)]
    return Bpe(merges, {s: i + 2 for i, s in enumerate(dict.fromkeys(names))})


def encoded(pieces: DataFrame, model: Bpe) -> DataFrame:
    """(piece, tokens) of distinct pieces; the model is loaded once per task."""
    shared = pieces.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("array<int>")
    def encode(it: Iterator[pd.Series]) -> Iterator[pd.Series]:
        m = shared.value
        for s in it:
            yield s.map(m.encode)

    return pieces.select("piece").distinct().withColumn("tokens", encode("piece"))


def model_tables(spark, model: Bpe) -> tuple[DataFrame, DataFrame]:
    """(rank, left, right, merged) and (token_id, token)."""
    merges = spark.createDataFrame([(i, a, b, a + b) for i, (a, b) in enumerate(model.merges)], "rank int, left string, right string, merged string")
    return merges, spark.createDataFrame([(i, t) for t, i in model.vocab.items()], "token_id int, token string")
