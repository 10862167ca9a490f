import pytest

#: Null ids, null, empty and blank texts, repeated rows, near copies, and columns named like those used inside.
ROWS = [
    (1, "Alpha beta gamma delta epsilon zeta eta theta", "en", "src1"),
    (2, "alpha beta gamma delta epsilon zeta eta theta", "en", "src1"),
    (2, "alpha beta gamma delta epsilon zeta eta theta", "en", "src1"),
    (3, None, None, None),
    (4, "", "fr", "src2"),
    (5, " \n\t ", "fr", "src2"),
    (None, "alpha beta gamma delta epsilon zeta eta theta", "en", "src3"),
    (None, "only here", "en", "src3"),
    (6, "one", "de", "x"),
    (7, "É" * 300 + " " + "wort " * 400, "de", "src9"),
    (8, "É" * 300 + " " + "wort " * 400, "de", "src9"),
    (9, "Released under the MIT License.\n" + " ".join(f"w{i}" for i in range(300)), "en", "src4"),
    (10, "Intro\n" + " ".join(f"w{i}" for i in range(297)), "en", "src4"),
]


@pytest.fixture(scope="session")
def odd_docs(spark):
    df = spark.createDataFrame(ROWS, "doc_id long, text string, lang string, source string")
    return df.selectExpr("*", "length(text) as n_chars", "'x' as tk", "1 as id", "'t' as t", "true as in_mask", "0 as row", "'p' as point", "1 as `mask at`")


@pytest.fixture(scope="session")
def no_docs(odd_docs):
    return odd_docs.where("false")


@pytest.fixture(scope="session")
def texts(spark):
    """Documents of the smallest tables, by id."""
    rows = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text").collect()
    return {r[0]: r[1] or "" for r in rows}
