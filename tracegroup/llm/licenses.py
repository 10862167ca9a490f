"""Licence scans: normalised text held against licence templates by the Dice coefficient over word bigrams.

The sizes of two bigram sets bound their coefficient, so a piece of text is only held against templates
whose size allows the threshold. Notices that stand inside other text, or run over lines and paragraphs, are
found as windows of words.
"""

from __future__ import annotations

import re
from bisect import bisect_left, bisect_right, insort
from collections.abc import Iterator, Mapping
from heapq import heapify, heappop, heappush

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tracegroup.llm.common import small_batches

#: Notices that licences ask for or that name them, as published.
TEMPLATES: dict[str, str] = {
    "MIT-notice": "Released under the MIT License.",
    "Apache-2.0-notice": "Licensed under the Apache License, Version 2.0.",
    "GPL-3.0-notice": "This work is licensed under the GNU General Public License, version 3.",
    "CC-BY-NC-4.0-notice": "Licensed under CC BY-NC 4.0.",
    "CC-BY-4.0-notice": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "CC-BY-SA-4.0-notice": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
    "CC0-notice": "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work.",
    "Reserved": "All rights reserved.",
    "MIT": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "ISC": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    "Apache-2.0-header": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    "GPL-3.0-header": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details.",
    "MPL-2.0-header": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/.",
}

THRESHOLD = 0.8
_WORD = re.compile(r"[a-z0-9]+(?:\.[0-9]+)*")


def bigrams(text: str) -> frozenset[tuple[str, str]]:
    """Word pairs of the normalised text: lower case, words of letters and digits (a version number is one), signs left out."""
    words = _WORD.findall(text.lower())
    return frozenset(zip(words, words[1:], strict=False))


def dice(a: frozenset, b: frozenset) -> float:
    return 2 * len(a & b) / (len(a) + len(b)) if a or b else 0.0


class Templates:
    """Templates by size. Of sizes m and n the coefficient is at most 2 * min(m, n) / (m + n)."""

    def __init__(self, texts: Mapping[str, str], threshold: float):
        self.threshold = threshold
        self.sets = sorted(((len(b), name, b) for name, t in texts.items() if (b := bigrams(t))), key=lambda x: x[:2])
        self.first = {pair for _, _, b in self.sets for pair in b}
        self.words = {w for pair in self.first for w in pair}

    def bounds(self, size: int) -> tuple[float, float]:
        """Sizes whose coefficient with a set of `size` can reach the threshold."""
        t = self.threshold
        return size * t / (2 - t) - 1e-9, size * (2 - t) / t + 1e-9

    def matches(self, text: str) -> Iterator[tuple[str, float]]:
        found = bigrams(text)
        low, high = self.bounds(len(found))
        for n, name, b in self.sets:
            if low <= n <= high and (d := dice(found, b)) >= self.threshold:
                yield name, d

    def near(self, words: list[str]) -> list[tuple[int, str, frozenset]]:
        """Templates that some run of the words may reach the threshold with: at least the smallest size that allows it is shared."""
        met = self.first.intersection(zip(words, words[1:], strict=False))
        return [s for s in self.sets if met and len(s[2] & met) >= self.bounds(s[0])[0]]

    def windows(self, words: list[str], n: int, b: frozenset) -> list[tuple[float, int, int]]:
        """(dice, first word, last word) of runs of words that reach the threshold with a template of n bigrams, none over another.

        Best first, then the earlier, then the shorter; a run that meets a better one is cut short before it. A run
        that begins or ends outside the template, or with a bigram that it has again, is not better without it, so
        from each start it is followed to the next like it, or to the widest set: linear in the text, any size.
        """
        pairs = list(zip(words, words[1:], strict=False))
        widest = self.bounds(n)[1]
        again, last = {}, {}
        for i in range(len(pairs) - 1, -1, -1):
            if pairs[i] in b:
                again[i] = last.get(pairs[i], len(pairs))
                last[pairs[i]] = i

        def best(i: int, end: int) -> tuple[float, int, int] | None:
            seen, shared, out = set(), 0, None
            for j in range(i, min(end, again[i])):
                if pairs[j] not in seen:
                    seen.add(pairs[j])
                    if len(seen) > widest:
                        break
                    if pairs[j] in b:
                        shared += 1
                        d = 2 * shared / (len(seen) + n)
                        if d >= self.threshold and (out is None or -d < out[0]):
                            out = (-d, i, j)
            return out

        heap = [w for i in again if (w := best(i, len(pairs)))]
        heapify(heap)
        taken: list[tuple[int, int]] = []
        out = []
        while heap:
            d, i, j = heappop(heap)
            at = bisect_right(taken, (i, len(pairs)))
            if at and taken[at - 1][1] >= i:
                continue
            if at < len(taken) and j + 1 >= taken[at][0]:
                if w := best(i, taken[at][0] - 1):
                    heappush(heap, w)
                continue
            insort(taken, (i, j + 1))
            out.append((-d, i, j + 1))
        return out


def placed_words(text: str) -> tuple[list[int], list[int]]:
    """Where each word of the normalised text begins and ends in text; lower case may be longer than what it stands for."""
    lower = text.lower()
    spans = [m.span() for m in _WORD.finditer(lower)]
    if len(lower) != len(text):
        at = [i for i, c in enumerate(text) for _ in c.lower()]
        spans = [(at[low], at[high - 1] + 1) for low, high in spans]
    return [low for low, _ in spans], [high for _, high in spans]


def pieces(text: str) -> Iterator[tuple[str, int, int]]:
    """What may be a licence text: each line, each paragraph of several lines, and the whole, with its place."""
    at, paragraph = 0, 0
    lines = text.split("\n")
    for i, line in enumerate([*lines, ""]):
        if not line.strip():
            body = text[paragraph : max(at - 1, paragraph)]
            if "\n" in body.strip():
                yield body, paragraph, paragraph + len(body)
            paragraph = at + len(line) + 1
        elif i < len(lines):
            yield line, at, at + len(line)
        at += len(line) + 1
    if re.search(r"\n\s*\n", text):
        yield text, 0, len(text)


def scan(docs: DataFrame, templates: Mapping[str, str] = TEMPLATES, threshold: float = THRESHOLD, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """Per row of docs: id, licence (the best match's template or null), dice of it, and all matches as (template, dice, low, high).

    Matches are pieces of the text (lines, paragraphs, the whole) whose bigram set reaches the threshold with
    a template's, and the best runs of words anywhere in it that do and are no such piece, over line and paragraph
    ends too; low and high are character places. The best is the highest coefficient, then the first
    name, then the first place. Null, empty and one-word texts match nothing; repeated rows stay; other
    columns are not read. A piece is judged whole, however long.
    """
    known = Templates(templates, threshold)

    def found(body: str) -> list[dict]:
        words_of = _WORD.findall(body.lower())
        near = known.near(words_of)
        if not near:
            return []
        out = []
        for piece, low, high in pieces(body):
            out += [{"template": n, "dice": d, "low": low, "high": high} for n, d in known.matches(piece)]
        starts, ends = placed_words(body)
        had = {(m["template"], bisect_left(starts, m["low"]), bisect_right(ends, m["high"]) - 1) for m in out}
        for n, name, b in near:
            out += [{"template": name, "dice": d, "low": starts[i], "high": ends[j]} for d, i, j in known.windows(words_of, n, b) if (name, i, j) not in had]
        return sorted(out, key=lambda m: (-m["dice"], m["template"], m["low"]))

    kind = pa.list_(pa.struct([("template", pa.string()), ("dice", pa.float64()), ("low", pa.int64()), ("high", pa.int64())]))

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            all_ = [found(t.as_py() or "") for t in batch.column("t")]
            best = [m[0] if m else None for m in all_]
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array([b and b["template"] for b in best], pa.string()), pa.array([b and b["dice"] for b in best], pa.float64()), pa.array(all_, kind)], ["id", "licence", "dice", "matches"])

    out = small_batches(docs).select(F.col(f"`{id_col}`").cast("long").alias("id"), F.col(f"`{text}`").alias("t")).mapInArrow(run, "id long, licence string, dice double, matches array<struct<template:string,dice:double,low:long,high:long>>")
    return out.withColumnRenamed("id", id_col)
