import hashlib
import random
from collections import Counter

import numpy as np
import pytest

from tests.llm.conftest import ROWS
from tracegroup.llm import suffix_dedup as s


def brute(bodies, length):
    seen = Counter(b[a : a + length] for b in bodies for a in range(len(b) - length + 1))
    out = []
    for b in bodies:
        gone = np.zeros(len(b) + 1, bool)
        for a in range(len(b) - length + 1):
            if seen[b[a : a + length]] > 1:
                gone[a : a + length] = True
        kept = bytes(c for c, g in zip(b, gone) if not g)
        out.append((len(b), int(gone[:-1].sum()), int((gone[1:] < gone[:-1]).sum()), hashlib.sha256(kept).hexdigest()))
    return out


@pytest.mark.parametrize("hot", [4096, 1])
def test_against_brute_force(spark, hot):
    rng = random.Random(5)
    words = ["".join(rng.choice("abcd") for _ in range(rng.randint(1, 7))) for _ in range(60)]
    passage = " ".join(rng.choice(words) for _ in range(70))
    bodies = [" ".join(rng.choice(words) for _ in range(rng.randint(0, 160))) for _ in range(30)]
    bodies += [b[: len(b) // 2] + passage + b[len(b) // 2 :] for b in bodies[:12]]
    bodies += [bodies[3], bodies[3], "x" * 500, "ab" * 300, bodies[5][:90] + "é" + bodies[5][91:], "", passage, passage[1:], passage[:-1]]
    df = spark.createDataFrame(list(enumerate(bodies)), "doc_id long, text string")
    for length, gram in ((80, 24), (64, 40)):
        got = {r[0]: tuple(r[1:]) for r in s.without_repeats(df, length=length, gram=gram, hot=hot).collect()}
        want = brute([b.encode() for b in bodies], length)
        assert [got[i] for i in range(len(bodies))] == want


def test_odd_rows(odd_docs, no_docs):
    got = sorted((str(r[0]), *r[1:]) for r in s.without_repeats(odd_docs).collect())
    want = sorted((str(r[0]), *w) for r, w in zip(ROWS, brute([(r[1] or "").encode() for r in ROWS], 400)))
    assert got == want
    assert s.without_repeats(no_docs).count() == 0


def test_suffix_sort_order():
    rng = np.random.default_rng(3)
    data = rng.integers(97, 99, 400).astype(np.uint8)
    start = rng.permutation(400)[:120]
    group = np.sort(rng.integers(0, 5, 120))
    ends = np.array([400])
    order = s.sort_suffixes(s.Extensions(data), group, start, np.zeros(120, np.int64), ends)
    keys = [(group[i], data[start[i] :].tobytes()) for i in order]
    assert keys == sorted(keys) and sorted(order) == list(range(120))


def test_long_text_in_pieces(monkeypatch, spark):
    monkeypatch.setattr(s, "SLICE_BYTES", 600)
    rng = random.Random(8)
    body = "".join(rng.choice("abcdefgh ") for _ in range(4000))
    data = np.frombuffer(body.encode(), np.uint8)
    whole, _ = s.anchors(data, np.array([0, 4000]), 400, 128)
    parts = set()
    for a, b in s._pieces(4000, 400):
        place, _ = s.anchors(data[a:b], np.array([0, b - a]), 400, 128)
        parts |= set((place + a).tolist())
    assert parts == set(whole.tolist())


def test_crowded_cores_over_batches(spark):
    rng = random.Random(11)
    passage = "".join(rng.choice("abcdefgh ") for _ in range(150))
    bodies = ["".join(rng.choice("xyz ") for _ in range(rng.randint(0, 90))) + passage + "".join(rng.choice("xyz ") for _ in range(rng.randint(0, 90))) for _ in range(25)]
    bodies += ["so it is. " * k for k in (9, 30, 31, 32)] + ["a" * 300, passage, passage[:100] + "\0" * 40, passage[:100]]
    df = spark.createDataFrame(list(enumerate(bodies)), "doc_id long, text string")
    rows = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 3)
    try:
        got = {r[0]: tuple(r[1:5]) for r in s.without_repeats(df, length=90, gram=30, hot=2, rest=True).collect()}
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", rows)
    assert [got[i] for i in range(len(bodies))] == brute([b.encode() for b in bodies], 90)


def test_each_string_has_one_anchor():
    rng = random.Random(2)
    for body in ("".join(rng.choice("ab") for _ in range(900)), "no end " * 120, "".join(rng.choice("abcdefgh ") for _ in range(900))):
        data = np.frombuffer(body.encode(), np.uint8)
        place, _, low, high = s.owned_anchors(data, np.array([0, len(data)]), 100, 30)
        owned = Counter(q for a, b in zip(low.tolist(), high.tolist()) for q in range(a, b + 1))
        assert owned == Counter(range(len(data) - 99))
        assert (place - high >= 0).all() and (place - low <= 70).all()
