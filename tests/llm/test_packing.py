import random
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from tests.llm.conftest import ROWS
from tracegroup.llm import packing as p

WHOLE = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))


def ids_of(text):
    return [*WHOLE.encode(text or "", add_special_tokens=False).ids, 0]


def check(rows, size, got):
    by_doc = defaultdict(list)
    for r in got:
        by_doc[str(r["doc_id"]), r["piece"]].append(r)
    want = Counter()
    for i, t in rows:
        ids = ids_of(t)
        first = len(ids) % size or size
        cuts = [0, *range(first, len(ids) + 1, size)]
        for k, (a, b) in enumerate(zip(cuts, cuts[1:])):
            want[str(i), k, a, b - a, zlib.crc32(np.array(ids[a:b], "<u4").tobytes())] += 1
    assert Counter((str(r["doc_id"]), r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in got) == want
    bins = defaultdict(list)
    for r in got:
        bins[r["sequence_id"]].append((r["offset"], r["length"]))
    for pieces in bins.values():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at
            at += length
        assert at <= size
    return len(bins)


def test_odd_rows(odd_docs, no_docs):
    rows = [(r[0], r[1]) for r in ROWS]
    for size in (2048, 64, 7):
        check(rows, size, p.pack(odd_docs, size=size).collect())
    assert p.pack(no_docs).count() == 0


def test_documents(spark, texts):
    rows = list(texts.items())
    n = check(rows, 2048, p.pack(spark.createDataFrame(rows, "doc_id long, text string").repartition(5)).collect())
    total = sum(len(ids_of(t)) for t in texts.values())
    assert n <= -(-total // 2048) + 2


@pytest.mark.parametrize("text", ["", " ", "a  b", "a \n b", "\n\na", "a\tb c", "it's don't 's a 's", "  lead", "trail ", "a　 b", "<|endoftext|> hi", "a\n'll b", "1 2 33 $ $$ %% é è\nÉ ", "é é\nà ü", "x" * 3000, "a\x85b \xa0 c"])
def test_ids_are_those_of_the_tokenizer(text):
    tokens = p.WordTokens()
    for texts in ([text], ["left", text, "right hand", text]):
        import pyarrow as pa

        from tracegroup.llm.common import bytes_of

        ids, cut = tokens.encode(*bytes_of(pa.array(texts)))
        for t, a, b in zip(texts, cut, cut[1:]):
            assert ids[a:b].tolist() == WHOLE.encode(t, add_special_tokens=False).ids


def test_fullest_is_a_best_subset():
    rng = random.Random(3)
    for _ in range(60):
        size = rng.randint(5, 40)
        counts = Counter(rng.randint(1, size) for _ in range(rng.randint(1, 9)))
        seed = max(counts)
        sums = {seed}
        rest = list((counts - Counter([seed])).elements())
        for x in rest:
            sums |= {s + x for s in sums if s + x <= size}
        chosen = p.fullest(dict(counts), seed, size)
        assert sum(chosen) == max(sums) and not Counter(chosen) - counts


def test_plan_uses_every_piece():
    rng = random.Random(4)
    h = {x: rng.randint(1, 500) for x in rng.sample(range(1, 2049), 300)}
    plan = p.minimum_bin_slack(h)
    assert {x: int(v[-1]) for x, v in plan.upto.items()} == h
    assert plan.sequences <= least_sequences(h, 2048) * 1.01 + 1


def least_sequences(h, size):
    """No plan has fewer: tokens over the size; or, for any k, pieces over half a sequence each alone, those over size - k closed to pieces of k and more."""
    best = -(-sum(x * n for x, n in h.items()) // size)
    for k in range(1, size // 2 + 1):
        closed = sum(n for x, n in h.items() if x > size - k)
        half = [(x, n) for x, n in h.items() if size // 2 < x <= size - k]
        small = sum(x * n for x, n in h.items() if k <= x <= size // 2)
        alone = sum(n for _, n in half)
        room = sum((size - x) * n for x, n in half)
        best = max(best, closed + alone + max(0, -(-(small - room) // size)))
    return best


def test_words_are_forgotten_at_the_end_of_a_task():
    import pyarrow as pa

    tokens = p.WordTokens()
    texts = ["one two three " * 30000 + "end", "", "four five"]
    batch = pa.RecordBatch.from_pydict({"id": pa.array([1, 2, 3]), "t": pa.array(texts)})
    got = list(p.tokenised(iter([batch, batch]), tokens))
    assert tokens.key is None and len(tokens.ids) == 0
    ids = [x[a:b] for _, x, c in got for a, b in zip(c[:-1], c[1:], strict=True)]
    for x, text in zip(ids, texts + texts, strict=True):
        assert np.array_equal(x, tokens.one(text.encode()))
