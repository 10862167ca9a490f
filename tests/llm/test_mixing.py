import hashlib
import random
import re
from collections import defaultdict

from pyspark.sql import functions as F

from tests.llm.conftest import ROWS
from tracegroup.llm import mixing as m


def fill(budget, rooms, weights):
    """Whole-number water level over children, one by one."""
    left = {k for k in rooms if weights[k] > 0}
    got = dict.fromkeys(rooms, 0)
    while left:
        k = min(left, key=lambda c: (rooms[c] / weights[c], c))
        if rooms[k] * sum(weights[c] for c in left) <= weights[k] * budget:
            got[k] = rooms[k]
            budget -= rooms[k]
            left.remove(k)
        else:
            total = sum(weights[c] for c in left)
            for c in left:
                got[c] = min(rooms[c], weights[c] * budget // total)
            break
    return got


def plain(rows, config):
    leaves = defaultdict(list)
    for i, t, lang, source in rows:
        n = len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))
        leaves[(source or "")[:4], lang or "", source or ""].append((i, n))
    tokens = {k: sum(n for _, n in v) for k, v in leaves.items()}
    room = {k: v * config.most_epochs for k, v in tokens.items()}
    w = lambda level, name: config.weights.get(level, {}).get(name, 1)
    up = lambda keys: {x: sum(v for k, v in room.items() if k[: len(x)] == x) for x in keys}
    total = sum(tokens.values()) * config.share_of_all // 1000
    out, budgets = {}, {}
    domains = fill(total, up({k[:1] for k in room}), {k[:1]: w("domain", k[0]) for k in room})
    for d, b in domains.items():
        langs = {k[:2] for k in room if k[:1] == d}
        for l, c in fill(b, up(langs), {x: w("lang", x[1]) for x in langs}).items():
            own = {k: room[k] for k in room if k[:2] == l}
            budgets |= fill(c, own, {k: w("source", k[2]) for k in own})
    for k, docs in leaves.items():
        epochs = budgets[k] // tokens[k] if tokens[k] else 0
        left, at = budgets[k] - epochs * tokens[k], 0
        place = lambda i: hashlib.md5(f"{config.seed}|{epochs}|{'null' if i is None else i}".encode()).hexdigest()
        for p in sorted({place(i) for i, _ in docs}):
            for i, n in docs:
                if place(i) == p:
                    out.setdefault((str(i), k, n), []).append(epochs + (left > 0 and at < left))
            at += sum(n for i, n in docs if place(i) == p)
    return budgets, {k: sorted(v) for k, v in out.items()}


def compare(df, rows, config):
    got = m.mix(df, F.substring("source", 1, 4), config).collect()
    budgets, copies = plain(rows, config)
    found = defaultdict(list)
    for r in got:
        k = (r["domain"], r["lang"], r["source"])
        assert r["budget"] == budgets[k]
        found[str(r["doc_id"]), k, r["n_tokens"]].append(r["copies"])
    assert {k: sorted(v) for k, v in found.items()} == copies


def test_against_plain(spark, odd_docs, no_docs):
    rng = random.Random(6)
    rows = [(i, "w " * rng.randint(0, 90), rng.choice(["en", "de", None]), rng.choice(["web1", "web2", "books3", "code4", None])) for i in range(400)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    for config in (m.MixConfig(), m.MixConfig({"domain": {"web1": 5, "code": 0}, "lang": {"en": 3}}, 700), m.MixConfig({"domain": {"book": 40}}, 900, most_epochs=3, digits=1), m.MixConfig(share_of_all=5000)):
        compare(df, rows, config)
    compare(odd_docs, ROWS, m.MixConfig(share_of_all=600))
    assert m.mix(no_docs, F.col("source")).count() == 0


def test_mixed_rows(odd_docs):
    config = m.MixConfig(share_of_all=500, most_epochs=1)
    out = m.mixed(odd_docs, F.lit("d"), config)
    gone = {r["doc_id"] for r in m.mix(odd_docs, F.lit("d"), config).where("copies = 0").collect()}
    assert out.columns == odd_docs.columns and gone
    assert out.count() == odd_docs.where(~F.coalesce(F.col("doc_id").isin([g for g in gone if g is not None]), F.lit(None in gone))).count()


def test_mixed_rows_of_equal_ids_in_several_leaves(spark):
    """Null ids and ids that repeat over sources: each leaf keeps what its own budget has room for."""
    rows = [(None if i % 3 == 0 else i // 5, f"{'w ' * (1 + i % 7)}{i}", ("en", "de", None)[i % 2 if i % 11 else 2], f"src{i % 5}") for i in range(300)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    config = m.MixConfig({"source": {"src1": 0}}, 600, most_epochs=1)
    domain = F.when(F.col("source") == "src4", "other").otherwise("web")
    kept = m.mix(df, domain, config).where("copies = 1")
    assert kept.where("doc_id is null").count() and m.mix(df, domain, config).where("copies = 0 and doc_id is null").count()
    out = m.mixed(df, domain, config)
    key = lambda frame: sorted(str(tuple(r)) for r in frame.selectExpr("doc_id", "coalesce(lang, '')", "source", "n_tokens").collect())
    got = out.withColumn("n_tokens", F.size(F.split(F.trim("text"), " ")).cast("long"))
    assert key(got) == key(kept)
