from tracegroup.llm import quotes as q

ROWS = [
    (1, 0, "user", "How do I sort  a list?\nIt is long.", "x"),
    (1, 1, "assistant", "> how do i SORT a list?\nUse sorted().", "x"),
    (1, 2, "user", "Thanks.", "x"),
    (1, 3, "user", "On Monday, someone wrote:\n>> How do I sort a list?\n> Use sorted().\n> never said\n\nWhat about tuples?\n", "x"),
    (2, 1, "user", "> How do I sort a list?\nother place", "x"),
    (2, 0, None, None, "x"),
    (2, None, "user", "> no turn", "x"),
    (None, 4, "user", "> Thanks.\nno conversation", "x"),
    (3, 0, "user", "> mine\nmine", "x"),
    (3, 0, "user", "> mine\nmine", "x"),
    (3, 1, "user", "  > > mine\n>mine\n>", "x"),
    (4, 0, "user", "he wrote:\nno quote follows", "x"),
]


def test_links(spark):
    df = spark.createDataFrame(ROWS, "conv_id long, turn long, role string, text string, body string")
    got = {(r["conv_id"], r["turn"]): r for r in q.linked_messages(df).collect()}
    assert q.linked_messages(df).count() == len(ROWS)
    r = got[1, 1]
    assert (r["body"], r["reply_to"], r["n_quoted"], r["n_linked"], r["deepest"]) == ("Use sorted().", 0, 1, 1, 1)
    r = got[1, 3]
    assert (r["body"], r["reply_to"], r["n_quoted"], r["n_linked"], r["deepest"]) == ("What about tuples?", 1, 3, 2, 2)
    assert got[2, 1]["reply_to"] is None and got[2, 1]["n_quoted"] == 1
    assert got[2, 0]["body"] == "" and got[2, 0]["rendered"] == "<||>\n\n"
    assert got[None, 4]["n_quoted"] == 0 and got[None, 4]["body"] == "no conversation"
    assert got[3, 0]["n_quoted"] == 1 and got[3, 0]["reply_to"] is None
    assert (got[3, 1]["reply_to"], got[3, 1]["n_quoted"], got[3, 1]["deepest"], got[3, 1]["body"]) == (0, 2, 2, "")
    assert got[4, 0]["body"] == "he wrote:\nno quote follows"
    assert q.linked_messages(df.where("false")).count() == 0


def test_no_python_in_the_plan(spark):
    df = spark.createDataFrame(ROWS, "conv_id long, turn long, role string, text string, body string")
    plan = q.linked_messages(df)._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan


def test_written_order(spark, tmp_path):
    df = spark.createDataFrame(ROWS, "conv_id long, turn long, role string, text string, body string")
    q.write_conversations(q.linked_messages(df), str(tmp_path / "out"))
    turns = [r["turn"] for r in spark.read.parquet(str(tmp_path / "out")).where("conv_id = 1").collect()]
    assert turns == [0, 1, 2, 3]


def test_passages_that_were_wrapped_anew(spark):
    rows = [
        (1, 0, "user", "One long line that is said first.\nAnd a second line.\n\nAnother paragraph.", "x"),
        (1, 1, "assistant", "> One long line\n> that is said\n> first. And a second line.\n\nYes.", "x"),
        (1, 2, "user", ">> another\n>> PARAGRAPH.\n> Yes.\nNo \x01 2.", "x"),
        (1, 3, "user", "> never\n> said\n>\n> No   \x02 2.", "x"),
        (1, 4, "user", "alone", "x"),
    ]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, thread string")
    out = q.threads(q.linked_messages(df))
    got = {r["turn"]: r for r in out.collect()}
    told = lambda r: (r["reply_to"], r["n_quoted"], r["n_linked"], r["n_passages"], r["n_passages_linked"], r["thread"])
    assert told(got[1]) == (0, 3, 0, 1, 1, 0)
    assert told(got[2]) == (1, 3, 1, 2, 2, 0)
    assert got[3]["n_passages"] == 2 and got[3]["n_passages_linked"] == 1 and got[3]["reply_to"] == 2 and got[3]["thread"] == 0
    assert got[4]["thread"] == 4 and q.threads(q.linked_messages(df.where("false"))).count() == 0


def test_threads_keep_rows_without_a_place(spark):
    df = spark.createDataFrame(ROWS, "conv_id long, turn long, role string, text string, body string")
    out = q.threads(q.linked_messages(df)).collect()
    assert len(out) == len(ROWS)
    assert {(r["conv_id"], r["turn"]): r["thread"] for r in out}[1, 3] == 0
    assert all((r["thread"] is None) == (r["conv_id"] is None or r["turn"] is None) for r in out)


def test_query_gives_threads_in_order(spark, monkeypatch):
    """Two threads that take turns in one conversation come back one after the other, answers after what they answer."""
    from tracegroup.llm import queries

    said = ["first question", "second question", "> first question\nfirst answer", "> second question\nsecond answer", "> first answer\nthanks for the first", "> second answer\nthanks for the second"]
    df = spark.createDataFrame([(1, i, "user", t) for i, t in enumerate(said)], "conv_id long, turn long, role string, text string").repartition(3)
    monkeypatch.setattr(queries, "table", lambda *_: df)
    got = queries.op10_quotes(spark, "")
    assert [r["turn"] for r in got.collect()] == [0, 2, 4, 1, 3, 5]
    assert "thread" not in got.columns
