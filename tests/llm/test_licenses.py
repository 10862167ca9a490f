import random

from tests.llm.conftest import ROWS
from tracegroup.llm import licenses as li


def brute(text):
    """Every piece against every template, without bounds."""
    found = []
    for piece, low, high in li.pieces(text):
        for name, t in li.TEMPLATES.items():
            a, b = li.bigrams(piece), li.bigrams(t)
            if a and (d := 2 * len(a & b) / (len(a) + len(b))) >= li.THRESHOLD:
                found.append((name, low, high))
    return sorted(found)


def test_against_brute_force(spark, texts):
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    for r in li.scan(df).collect():
        assert sorted((m["template"], m["low"], m["high"]) for m in r["matches"]) == brute(texts[r["doc_id"]])


def test_templates_find_themselves(spark):
    rows = [(i, f"Some title\n\n{t}\n\nand an end that says other things") for i, t in enumerate(li.TEMPLATES.values())]
    got = {r["doc_id"]: (r["licence"], r["dice"]) for r in li.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {i: (n, 1.0) for i, n in enumerate(li.TEMPLATES)}


def test_a_notice_over_several_lines(spark):
    text = li.TEMPLATES["MIT"].replace(", ", ",\n")
    (r,) = li.scan(spark.createDataFrame([(1, f"Head\n\n{text}\n\nTail words")], "doc_id long, text string")).collect()
    assert r["licence"] == "MIT"


def test_odd_rows(odd_docs, no_docs):
    got = li.scan(odd_docs).collect()
    assert sorted(str(r["doc_id"]) for r in got) == sorted(str(r[0]) for r in ROWS)
    assert [r["licence"] for r in got if r["doc_id"] == 9] == ["MIT-notice"]
    assert li.scan(no_docs).count() == 0


#: Notices as published, with blank lines between their paragraphs and wrapped lines.
LAID_OUT = {
    "MIT": li.TEMPLATES["MIT"].replace("conditions: ", "conditions:\n\n").replace("Software. THE", "Software.\n\nTHE").replace(", ", ",\n"),
    "Apache-2.0-header": li.TEMPLATES["Apache-2.0-header"].replace("License. You may", "License.\nYou may").replace("at http", "at\n\n    http").replace("2.0 Unless", "2.0\n\nUnless"),
    "GPL-3.0-header": li.TEMPLATES["GPL-3.0-header"].replace("version. This", "version.\n\nThis").replace("but WITHOUT", "but\nWITHOUT"),
}


def test_notices_inside_other_text(spark):
    other = " ".join(f"word{i}" for i in range(400))
    rows = [(i, f"{other}\n\n{t}\n\n{other}") for i, t in enumerate(LAID_OUT.values())]
    rows += [(i + 10, f"{other}\n{t}\n{other}") for i, t in enumerate(LAID_OUT.values())]
    rows += [(20, f"{other} Released\nunder the MIT License. {other}"), (21, "\u0130\u0130 " + f"{other} All rights reserved. {other}")]
    text = dict(rows)
    got = {r["doc_id"]: r for r in li.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    names = [*LAID_OUT]
    assert {i: (r["licence"], r["dice"]) for i, r in got.items()} == {**{i + k: (n, 1.0) for i, n in enumerate(names) for k in (0, 10)}, 20: ("MIT-notice", 1.0), 21: ("Reserved", 1.0)}
    for i, r in got.items():
        m = r["matches"][0]
        assert li.bigrams(text[i][m["low"] : m["high"]]) == li.bigrams(li.TEMPLATES[r["licence"]])


def test_windows_against_every_run():
    """The best run is the best of all runs; every run that reaches the threshold meets one that is taken."""
    rng, hit = random.Random(3), 0
    name = "Reserved words"
    known = li.Templates({name: "a b c d e a b f"}, 0.8)
    ((n, _, b),) = known.sets
    for _ in range(400):
        words = [rng.choice("aabbccddeeffx") for _ in range(10)] + rng.choice(["a b c d e a b f".split(), "a b c x d e a b f".split(), "a b c d e".split()]) * rng.randint(0, 2) + [rng.choice("abcdefxy") for _ in range(rng.randint(0, 14))]
        every = {(i, j): d for i in range(len(words)) for j in range(i + 1, len(words)) if (d := li.dice(li.bigrams(" ".join(words[i : j + 1])), b)) >= 0.8}
        got = known.windows(words, n, b)
        assert bool(every) == bool(got) and (not got or got[0][0] == max(every.values()))
        assert not every or known.near(words)
        for d, i, j in got:
            assert every[i, j] == d
        for i, j in every:
            assert any(i <= y and x <= j for _, x, y in got)
        hit += bool(got)
    assert hit > 100


def test_words_split_at_other_signs(spark):
    signs = " ".join(chr(0x4E00 + i) for i in range(3000))
    text = {1: "All\u00a0rights\u00a0reserved.", 2: "x y\nAll_rights_reserved", 3: "All,rights:reserved", 4: f"{signs} All rights reserved. {signs}"}
    for r in li.scan(spark.createDataFrame(list(text.items()), "doc_id long, text string")).collect():
        assert [(m["template"], m["low"], m["high"]) for m in r["matches"]] == brute(text[r["doc_id"]]) and (r["licence"], r["dice"]) == ("Reserved", 1.0)
