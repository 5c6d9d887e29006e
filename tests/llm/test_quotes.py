"""Quotation linking: passages wrapped anew, sentences, origins, reply order."""

import duckdb

from vecmend.llm import chat_quotes as C
from vecmend.llm import queries as Q

SCHEMA = "conv_id bigint, turn bigint, role string, text string"


def linked(spark, rows, schema=SCHEMA):
    return C.link(spark.createDataFrame(rows, schema).repartition(3)).collect()


def test_registered_queries_match_sql(spark, tiny):
    for name in ("op9_chat_formatting", "quoted_conversations"):
        con = duckdb.connect()
        con.execute(f"CREATE VIEW conversations AS SELECT * FROM '{tiny}/conversations.parquet'")
        want = con.execute(Q.ORACLE_SQL[name]).fetchall()
        got = [tuple(r) for r in Q.QUERIES[name](spark, tiny).collect()]
        assert sorted(map(str, got)) == sorted(map(str, want))
    assert sum(r[4] is not None for r in got) > len(got) / 3


def test_passages_wrapped_anew_link_and_stray_lines_do_not_win(spark):
    said = "The first sentence runs over one line. The second one follows it\nand ends here. A third."
    rows = [
        (1, 0, "user", said), (1, 1, "assistant", "Thanks"), (1, 2, "user", "> Thanks\nFine"),
        (1, 3, "user", "> The first sentence runs over\n> one line. The second one\n> follows it and ends here.\nYes"),
        (1, 4, "user", ">> The second one follows it and\n>> ends here.\n> Yes\nNo"), (1, 5, "user", "> nothing of the kind\nWhat"),
    ]
    got = {r.turn: (r.parent_turn, r.order_key.split("."), r.body) for r in linked(spark, rows)}
    pad = lambda *x: [f"{i:019d}" for i in x]
    assert got[2][:2] == (1, pad(1, 2)) and got[3][:2] == (0, pad(0, 3)) and got[4] == (3, pad(0, 3, 4), "No") and got[5][0] is None


def test_nested_replies_stand_below_their_own_branch(spark):
    rows = [(1, 0, "u", "root words here"), (1, 1, "u", "> root words here\nfirst branch"), (1, 2, "u", "> root words here\nsecond branch"), (1, 3, "u", "> first branch\nleaf")]
    assert [r.turn for r in sorted(linked(spark, rows), key=lambda r: r.order_key)] == [0, 1, 3, 2]


def test_tied_origins_repeats_nulls_and_clashing_columns(spark):
    rows = [(1, 0, "u", "same line", 1, "x"), (1, 70, "u", "same line", 1, "x"), (1, 71, "u", "> same line\na", 1, "x"), (1, 200, "u", "> same line\nb", 1, "x"), (1, 200, "u", "> same line\nb", 1, "x")]
    rows += [(None, 3, "u", "> same line", 1, "x"), (1, None, "u", "> same line", 1, "x"), (2, 5, "u", None, 1, "x"), (3, 0, "u", "w " * 30000 + ".", 1, "x"), (3, 1, "u", "> " + "w " * 30000 + ".", 1, "x")]
    got = [(r.conv_id, r.turn, r.parent_turn) for r in linked(spark, rows, "conv_id bigint, turn bigint, role string, text string, hash int, parent string")]
    assert sorted(got, key=str) == sorted([(1, 0, None), (1, 70, None), (1, 71, 70), (1, 200, 70), (1, 200, 70), (None, 3, None), (1, None, None), (2, 5, None), (3, 0, None), (3, 1, 0)], key=str)
    assert linked(spark, [r[:4] for r in rows[:0]] or [], SCHEMA) == []


def test_long_thread_and_hot_line(spark):
    rows = [(1, 0, "u", "start of it all")] + [(1, i, "u", f"> reply number {i - 1}\n> start of it all\nreply number {i}" if i > 1 else "> start of it all\nreply number 1") for i in range(1, 200)]
    got = {r.turn: r for r in linked(spark, rows)}
    assert got[1].parent_turn == 0 and len(got[1].order_key.split(".")) == 2
    assert all(len(r.order_key) == 20 * len(r.order_key.split(".")) - 1 for r in got.values())
