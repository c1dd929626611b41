from entlink.llm import quote_threads as q


def run(spark, rows):
    df = spark.createDataFrame([(*r, 1) for r in rows], "conv_id long, turn long, role string, text string, position int")
    return {(r.conv_id, r.turn, r.role): r for r in q.reply_ordered(df).collect()}


def test_nested_quotes_link_and_order(spark):
    rows = [
        (1, 0, "a", "Shall we meet?\nAt noon."),
        (1, 1, "b", "Where is the key?"),
        (1, 2, "c", "> Shall  we MEET?\n> At noon.\nYes, noon is fine."),
        (1, 3, "d", "On Monday c wrote:\n> Yes, noon is fine.\n>> Shall we meet?\n>> At noon.\nGood."),
        (1, 4, "e", "> > Shall we meet?\n> where IS the key?\nUnder the mat."),
        (1, 5, "f", "> nobody said this\nalone"),
        (2, 0, "a", "> Shall we meet?\nother conversation"),
    ]
    got = run(spark, rows)
    assert got[1, 2, "c"].parent_turn == 0 and got[1, 2, "c"].clean_text == "Yes, noon is fine."
    assert got[1, 3, "d"].parent_turn == 2 and got[1, 3, "d"].depth == 2 and got[1, 3, "d"].clean_text == "Good."
    assert got[1, 4, "e"].parent_turn == 1 and got[1, 4, "e"].quoted_lines == 2
    assert got[1, 5, "f"].parent_turn is None and got[1, 5, "f"].clean_text == "alone"
    assert got[2, 0, "a"].parent_turn is None
    order = sorted((r.position, r.turn) for r in got.values() if r.conv_id == 1)
    assert [t for _, t in order] == [0, 2, 3, 1, 4, 5] and [p for p, _ in order] == list(range(6))


def test_long_chain(spark):
    rows = [(1, 0, "u", "line 0")] + [(1, i, "u", f"> line {i - 1}\nline {i}") for i in range(1, 70)]
    got = run(spark, rows)
    assert all(got[1, i, "u"].depth == i and got[1, i, "u"].position == i for i in range(70))


def test_edges(spark):
    rows = [(None, 0, "u", None), (None, 1, "u", ""), (3, 0, "u", "same"), (3, 0, "u", "same"), (3, None, None, "> same"), (3, 1, "u", "> same"), (4, 0, "u", "x " * 100000)]
    df = spark.createDataFrame([(*r, 1) for r in rows], "conv_id long, turn long, role string, text string, depth int")
    got = q.reply_ordered(df).collect()
    assert len(got) == len(rows)
    assert [r.depth for r in got if r.conv_id == 3 and r.turn == 1] == [1]
    assert [r.parent_turn for r in got if r.conv_id == 3 and r.turn is None] == [None]
    assert sorted(r.position for r in got if r.conv_id == 3) == [0, 1, 2, 3]
    assert q.reply_ordered(df.where("false")).count() == 0


def test_query_and_sql_agree_on_quotes(spark, tmp_path):
    import random

    import duckdb

    from entlink.llm import queries

    rng = random.Random(5)
    said: dict = {}
    rows = []
    for conv in range(6):
        for turn in range(25):
            own = [f"Line {rng.randint(0, 40)}  of text." for _ in range(rng.randint(1, 3))]
            head = []
            for _ in range(rng.randint(0, 2)):
                old = said.get((conv, rng.randint(0, 24)))
                if old:
                    head += ["On day x wrote:"] * rng.randint(0, 1) + [">" * rng.randint(1, 2) + " " + x.upper() for x in old]
            said[conv, turn] = own
            rows.append((conv, turn, "user", "\n".join(head + own)))
    spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").write.parquet(f"{tmp_path}/conversations.parquet")
    got = queries.op5_quote_threads(spark, str(tmp_path))
    con = duckdb.connect()
    con.execute(f"CREATE VIEW conversations AS SELECT * FROM '{tmp_path}/conversations.parquet/*.parquet'")
    cols = ", ".join(got.columns)
    want = con.execute(f"SELECT {cols} FROM ({queries.ORACLES['op5_quote_threads']})").fetchall()
    key = lambda r: tuple(str(x) for x in r)
    assert sorted(map(tuple, got.collect()), key=key) == sorted(want, key=key)
    assert sum(r.depth > 1 for r in got.collect()) > 5
