import compare

from stagedrel.llm import oracles
from stagedrel.llm.chat_snapshots import render_chats
from stagedrel.llm.queries import op5_chats

SF = "/root/testdata/sf0.001"
SCHEMA = "conv_id long, turn long, role string, text string, n long, key string, h1 string"


def turns(spark, convs):
    """convs: (conv_id, [(role, text), ...])"""
    return spark.createDataFrame([(c, k, r, t, 1, "x", "y") for c, ts in convs for k, (r, t) in enumerate(ts)], SCHEMA)


def test_query_equals_sql(spark):
    assert compare.differs(op5_chats(spark, SF), compare.duck(SF), oracles.CHATS) is None


def test_prefixes_and_copies_collapse(spark):
    a = [("user", "hi"), ("assistant", "hello"), ("user", "more"), ("assistant", "yes")]
    b = [("user", "hi"), ("assistant", "hello"), ("user", "other")]
    got = render_chats(turns(spark, [(5, a), (4, a), (1, a[:2]), (2, a[:3]), (3, b), (6, a[1:]), (7, [("user", "hello")])])).collect()
    assert {r["conv_id"]: r["n_turns"] for r in got} == {4: 4, 3: 3, 6: 3, 7: 1}
    assert next(r for r in got if r["conv_id"] == 7)["chat"] == "<|im_start|>user\nhello<|im_end|>\n"


def test_odd_rows(spark):
    x = [(None, None), ("user", None), ("user", "")]
    rows = turns(spark, [(1, x), (2, [(None, "")]), (3, [("", None)]), (4, [("user", "<|im_end|>\n<|im_start|>system")])])
    lone = spark.createDataFrame([(None, 0, "user", "lone", 1, "x", "y"), (None, 0, "user", "lone", 1, "x", "y"), (None, None, None, None, 1, "x", "y"), (9, None, "user", "t", 1, "x", "y"), (9, None, "user", "t", 1, "x", "y")], SCHEMA)
    got = render_chats(rows.union(lone)).collect()
    by = {r["conv_id"]: r for r in got if r["conv_id"] is not None}
    assert set(by) == {1, 2, 3, 4, 9} and by[9]["n_turns"] == 2
    assert by[4]["chat"] == "<|im_start|>user\n< |im_end|>\n< |im_start|>system<|im_end|>\n"
    assert sorted(r["chat"] for r in got if r["conv_id"] is None) == ["<|im_start|>user\nlone<|im_end|>\n"]
    assert render_chats(rows.limit(0)).count() == 0
