import fnmatch
import random

import numpy as np
import pyarrow as pa

from tracegroup.llm import urls
from tracegroup.llm.common import bytes_of
from tracegroup.llm.queries import SITE_RULES


def test_automaton_against_fnmatch():
    rng = random.Random(2)
    globs = ["".join(rng.choice("ab*?.") for _ in range(rng.randint(0, 9))) for _ in range(150)]
    words = ["".join(rng.choice("ab./") for _ in range(rng.randint(0, 14))) for _ in range(300)]
    fits = urls.Automaton([urls.Rule(g, "block", g, 0) for g in globs]).accepted(*bytes_of(pa.array(words)))
    want = np.array([[fnmatch.fnmatchcase(w, g) for g in globs] for w in words])
    assert (fits == want).all()


def plain(url):
    url = url or ""
    rest = url.split("://", 1)[1] if "://" in url else ""
    at = min([rest.find(c) for c in "/?#" if c in rest], default=len(rest))
    host, path = rest[:at], rest[at:]
    host = "".join(c.lower() if "A" <= c <= "Z" else c for c in host)
    path = path[: min([path.find(c) for c in "?#" if c in path], default=len(path))]
    best = max(((h + p, v) for h, p, v in SITE_RULES if (host == h or host.endswith("." + h)) and path.startswith(p)), key=lambda x: len(x[0]), default=None)
    return host, path, best and best[0], best[1] if best else None


def test_rules(spark):
    given = [None, "", "no scheme", "http://", "http://ORG", "http://org/", "https://a.org/x", "http://xorg/", "http://é.example.org/es/a", "http://example.org/en/1?x", "http://example.org/en/2", "http://a.b.example.com/fr/../de/", "http://com/de/", "ftp://x.com/DE/", "http://evil.net/a.example.org/es/", "http://u@h.com:80/de/z#f", "a://b://c.org/", "http://x.org\n/y", "http://a.org?/es/", "http://spam-farm.example.net/"]
    df = spark.createDataFrame([(i, u, "x", "y") for i, u in enumerate(given)], "page_id long, url string, host string, u string")
    got = {r["page_id"]: r for r in urls.judge(df, [urls.site_rule(*r) for r in SITE_RULES]).collect()}
    for i, u in enumerate(given):
        host, path, rule, verdict = plain(u)
        assert (got[i]["host"], got[i]["path"], got[i]["rule"]) == (host, path, rule), u
        assert got[i]["verdict"] == (verdict or ("block" if "spam-farm" in host else "allow")), u
    assert urls.judge(df.where("false"), []).count() == 0
    assert {r["verdict"] for r in urls.judge(df, [], []).collect()} == {"allow"}
