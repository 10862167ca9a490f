import random

import pytest

from tracegroup.operators import temporal
from tracegroup.sources import storage


def test_range_join_against_all_pairs(spark):
    rng = random.Random(3)
    left = [(i, rng.choice([None, rng.randrange(-50, 300)])) for i in range(60)]
    right = [(i, rng.choice([None, rng.randrange(-50, 300)])) for i in range(60)] + [(99, 7), (99, 7)]
    a, b = spark.createDataFrame(left, "l long, at long"), spark.createDataFrame(right, "r long, then long")
    got = sorted((r["l"], r["r"]) for r in temporal.range_join(a, b, "at", "then", 17).collect())
    want = sorted((x, y) for x, s in left for y, t in right if s is not None and t is not None and 0 <= t - s < 17)
    assert got == want and want
    assert temporal.range_join(a.where("false"), b, "at", "then", 17).count() == 0


def test_as_of_join_takes_the_latest(spark):
    left = spark.createDataFrame([(1, "a", 5), (2, "a", 4), (3, "a", 0), (4, "b", 9), (5, None, 9), (6, "a", 5)], "id long, user string, at long")
    right = spark.createDataFrame([("a", 4, 10), ("a", 4, 11), ("a", 5, 12), ("a", 6, 13), ("c", 1, 14)], "user string, at long, item long")
    got = {r["id"]: (r["item"], r["since"]) for r in temporal.as_of_join(left, right, "user", "at", "item").collect()}
    assert got == {1: (12, 5), 2: (11, 4), 3: (None, None), 4: (None, None), 5: (None, None), 6: (12, 5)}
    assert temporal.as_of_join(left, right.where("false"), "user", "at", "item").where("item is not null").count() == 0


@pytest.mark.parametrize("master, one", [("local", True), ("local[*]", True), ("local[4,2]", True), ("local-cluster[3,2,1000]", False), ("yarn", False), ("spark://host:7077", False)])
def test_own_folder_only_on_one_machine(master, one):
    assert storage.on_one_machine(master) == one


def test_doc_copies_moves_no_text(spark):
    """Every shuffle of the categories and, keyed, of the reports carries hashes instead of sentences."""
    from tracegroup.sources import workloads as wl

    plain, hashed = (wl.doc_copies(spark, "/root/testdata/sf0.001", keyed=k) for k in (False, True))
    assert dict(hashed.dtypes)["frames"] == "array<bigint>"
    of = lambda df: sorted(map(tuple, df.select("report_id", "category_id", "n").collect()))
    assert of(plain.selectExpr("*", "size(frames) as n")) == of(hashed.selectExpr("*", "size(frames) as n"))
