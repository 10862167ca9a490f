import hashlib
import random
from collections import defaultdict

from tests.llm.conftest import ROWS
from tracegroup.llm import exact_dedup as x


def test_fingerprints_compose():
    rng = random.Random(1)
    for n in (0, 1, x.CHUNK - 1, x.CHUNK, x.CHUNK + 1, 3 * x.CHUNK + 77):
        body = rng.randbytes(n)
        value = 0
        for b in reversed(body):
            value = (value * x.BASE + b) % x.PRIME
        assert x.fingerprint(body) == value
        cut = rng.randrange(n + 1)
        assert x.combine([(x.fingerprint(body[:cut]), cut), (x.fingerprint(body[cut:]), n - cut)]) == value


def expected(rows):
    groups = defaultdict(list)
    for i, t in rows:
        groups[(t or "").encode().lower()].append(i)
    return sorted((str(i), str(max((j for j in groups[k] if j is not None), default=None)), len(groups[k]), hashlib.sha256(k).hexdigest()) for i, t in rows for k in [(t or "").encode().lower()])


def found(df):
    return sorted((str(r["doc_id"]), str(r["keep_id"]), r["group_size"], r["text_sha256"]) for r in df.collect())


def test_odd_rows_and_collisions(odd_docs):
    rows = [(r[0], r[1]) for r in ROWS]
    for options in ({}, {"prime": 13}, {"local_bytes": 1}, {"prime": 7, "local_bytes": 1}, {"parallel_bytes": 100}):
        out = x.exact_groups(odd_docs, **options).collect()
        assert sorted((str(r["doc_id"]), str(r["keep_id"]), r["group_size"], r["text_sha256"]) for r in out) == expected(rows)
        kept = defaultdict(int)
        for r in out:
            kept[r["text_sha256"]] += r["kept"]
        assert set(kept.values()) == {1}


def test_drop_keeps_columns(odd_docs, no_docs):
    out = x.drop_exact(odd_docs)
    assert out.columns == odd_docs.columns
    assert out.count() == len({(r[1] or "").lower() if (r[1] or "").isascii() else r[1] for r in ROWS})
    assert x.drop_exact(no_docs).count() == 0 and x.exact_groups(no_docs).count() == 0


def test_huge_text_in_chunks(spark):
    body = "Ab" * 1_500_000
    df = spark.createDataFrame([(1, body), (2, body.lower()), (3, body[:-1] + "c")], "doc_id long, text string")
    out = {r["doc_id"]: (r["keep_id"], r["group_size"]) for r in x.exact_groups(df, parallel_bytes=1 << 20).collect()}
    assert out == {1: (2, 2), 2: (2, 2), 3: (3, 1)}
