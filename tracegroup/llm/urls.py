"""URL filters: a bit-parallel wildcard automaton over canonical URLs.

All glob rules are packed side by side into the bits of a few 64-bit words. One Shift-And step per
character moves every rule of every URL of a batch at once; a star is a state that may stay.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tracegroup.llm.common import bytes_of


@dataclass(frozen=True)
class Rule:
    """A glob over the canonical URL `.host/path`. In it `*` is any run of bytes, `~` any run without a slash, `?` one byte."""

    glob: str
    verdict: str
    name: str
    rank: int


def site_rule(host: str, path: str, verdict: str) -> Rule:
    """A host, its subdomains, and paths that start with `path`. Longer rules rank higher."""
    return Rule(f"~.{host}{path}*", verdict, host + path, len(host + path))


#: Globs that judge what no site rule fits.
DEFAULT_GLOBS: tuple[tuple[str, str], ...] = (("*.spam-farm.*", "block"), ("*.cheap-pills.*", "block"), ("*.casino*", "block"), ("*/wp-login*", "block"), ("*/cgi-bin/*", "block"))


class Automaton:
    """Masks of all rules. Rule r occupies the bits first[r] to last[r]; the last accepts."""

    def __init__(self, rules: Sequence[Rule]):
        self.rules = list(rules)
        states: list[tuple[str, int]] = []
        self.first, self.last, begin, stay = [], [], [], []
        for r in self.rules:
            self.first.append(len(states))
            begin.append(len(states))
            states.append(("", -1))  # the empty prefix
            for b in r.glob.encode():
                if chr(b) in "*~":
                    stay.append((len(states) - 1, chr(b)))
                else:
                    states.append((chr(b), b))
            self.last.append(len(states) - 1)
        self.words = max(1, -(-len(states) // 64))
        self.step = np.zeros((256, self.words), np.uint64)
        self.loop = np.zeros((256, self.words), np.uint64)
        self.start = np.zeros(self.words, np.uint64)
        for i, (c, b) in enumerate(states):
            at, bit = i // 64, np.uint64(1 << (i % 64))
            if c == "?":
                self.step[:, at] |= bit
            elif b >= 0:
                self.step[b, at] |= bit
        for i in begin:
            self.start[i // 64] |= np.uint64(1 << (i % 64))
        for i, c in stay:
            at, bit = i // 64, np.uint64(1 << (i % 64))
            self.loop[:, at] |= bit
            if c == "~":
                self.loop[ord("/"), at] &= ~bit

    def accepted(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """rows x rules: whether each rule fits each whole URL."""
        n = len(offsets) - 1
        length = np.diff(offsets)
        order = np.argsort(-length, kind="stable")
        begin, size = offsets[:-1][order], length[order]
        state = np.repeat(self.start[None, :], n, 0)
        one, top = np.uint64(1), np.uint64(63)
        for i in range(int(size.max(initial=0))):
            live = int(np.searchsorted(-size, -i, "left"))
            d, c = state[:live], data[begin[:live] + i]
            moved = d << one
            moved[:, 1:] |= d[:, :-1] >> top
            state[:live] = (moved & self.step[c]) | (d & self.loop[c])
        out = np.empty((n, len(self.rules)), bool)
        for r, i in enumerate(self.last):
            out[order, r] = (state[:, i // 64] >> np.uint64(i % 64)) & one != 0
        return out


def judge(pages: DataFrame, rules: Sequence[Rule], globs: Sequence[tuple[str, str]] = DEFAULT_GLOBS, otherwise: str = "allow", id_col: str = "page_id", url: str = "url") -> DataFrame:
    """Per row of pages: id, host, path, rule, verdict and which glob fitted.

    Host: after the first `://` up to `/`, `?`, `#` or the end, A-Z lower-cased; path: from there up to `?`,
    `#` or the end; without `://`, and for null, both are empty. Of the site rules that fit, the one of the
    highest rank decides (equal ranks: the first given). If none does, `rule` is null and the first fitting
    glob decides, else `otherwise`. A glob that fits beside a site rule is reported but has no effect.
    Repeated rows stay, other columns are not read, an empty table gives an empty result. A batch takes one
    step per byte of its longest URL, but only over the URLs that are that long: the cost is bytes, not rows
    times the longest.
    """
    ranked = sorted(rules, key=lambda r: -r.rank)
    automaton = Automaton([*ranked, *(Rule(g, v, g, 0) for g, v in globs)])
    rest = F.when(F.instr(F.col("u"), "://") > 0, F.expr("substring(u, instr(u, '://') + 3)")).otherwise("")
    host = F.regexp_extract("rest", r"^([^/?#]*)", 1)
    path = F.regexp_extract("rest", r"^[^/?#]*([^?#]*)", 1)
    # [^...] classes match line breaks too, so hosts and paths are taken byte for byte
    parts = pages.select(F.col(f"`{id_col}`").cast("long").alias("id"), F.coalesce(F.col(f"`{url}`"), F.lit("")).alias("u")).withColumn("rest", rest)
    parts = parts.select("id", F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz").alias("host"), path.alias("path"))
    names = np.array([r.name for r in ranked] + [None], object)
    said = [r.verdict for r in ranked]

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            data, offsets = bytes_of(batch.column("canonical"))
            fits = automaton.accepted(data, offsets)
            site, glob = fits[:, : len(ranked)], fits[:, len(ranked) :]
            won = np.where(site.any(1), site.argmax(1) if len(ranked) else 0, len(ranked))
            hit = np.where(glob.any(1), glob.argmax(1) if len(globs) else 0, len(globs))
            by_glob = np.array([v for _, v in globs] + [otherwise], object)[hit]
            verdict = np.where(won < len(ranked), np.array([*said, ""], object)[won], by_glob)
            cols = [batch.column("id"), batch.column("host"), batch.column("path"), pa.array(names[won], pa.string()), pa.array(verdict, pa.string()), pa.array(np.array([g for g, _ in globs] + [None], object)[hit], pa.string())]
            yield pa.RecordBatch.from_arrays(cols, ["id", "host", "path", "rule", "verdict", "glob"])

    out = parts.select("id", "host", "path", F.concat(F.lit("."), "host", "path").alias("canonical")).mapInArrow(run, "id long, host string, path string, rule string, verdict string, glob string")
    return out.withColumnRenamed("id", id_col)
