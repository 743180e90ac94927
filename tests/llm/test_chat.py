from pyspark.sql import functions as F

from detectlab.llm import chat


def test_roles_of_conversations_not_learned(spark):
    turns = spark.read.parquet("/root/testdata/sf0.01/conversations.parquet")
    plain = chat.transcripts_of(turns)
    test = F.pmod(F.xxhash64("conv_id"), F.lit(4)) == 2
    model = chat.fit(plain.where(~test))
    got = {r.conv_id: r for r in chat.parse(plain.where(test), model).collect()}
    want = {}
    for r in sorted(turns.where(test).collect(), key=lambda r: (r.conv_id, r.turn)):
        if r.text.strip():
            want.setdefault(r.conv_id, []).append((r.role, r.text.strip()))
    right = sum(list(zip(got[c].roles, got[c].turns)) == w for c, w in want.items())
    assert len(want) > 15 and right >= 0.95 * len(want)


def test_canonical_form_is_read_back(spark):
    model = chat.fit(chat.transcripts_of(spark.read.parquet("/root/testdata/sf0.001/conversations.parquet")))
    turns = [(0, "be kind"), (1, "what?\n\nnote: 3 items\n- x"), (2, "this.\nhttp://a.b/c")]
    assert chat.turns_of(chat.render(turns), model) == turns
    assert chat.turns_of("Human: hi\nGPT: hello there.\nmore\nQ: so?", model) == [(1, "hi"), (2, "hello there.\nmore"), (1, "so?")]


def test_odd_rows(spark):
    rows = [(1, 0, "user", "a"), (1, 0, "user", "a"), (1, None, None, None), (None, 1, "assistant", "b"), (2, 5, "tool", "x" * 100000), (3, 0, "user", None), (4, 2500, "user", "far"), (4, 1, "system", "near")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").selectExpr("*", "1 as part")
    plain = chat.transcripts_of(df)
    model = chat.fit(plain)
    got = chat.parse(plain, model).collect()
    assert len(got) == 7 and sum(r.n_turns for r in got) == 6
    assert chat.parse(plain.limit(0), model).count() == 0 and chat.fit(plain.limit(0)).start.shape == (6,)
