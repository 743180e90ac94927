from detectlab.llm import chat, queries


def test_op9_learns_from_all_and_tells_parts_apart(spark, tmp_path, monkeypatch):
    rows = [(c, k, ("user", "assistant")[k % 2], f"text {c} {k}.") for c in range(40) for k in range(4)] + [(99, k, ("user", "assistant")[k % 2], f"t{k}") for k in range(2500)]
    spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").coalesce(1).write.parquet(f"{tmp_path}/conversations.parquet")
    fit, seen = chat.fit, []
    monkeypatch.setattr(chat, "fit", lambda t: [seen.extend(r.conv_id for r in t.select("conv_id").collect()), fit(t)][1])
    got = queries.op9_chat_format(spark, str(tmp_path)).collect()
    assert sorted(seen) == [*range(40), 99, 99, 99]
    assert sorted((r.part, r.n_turns) for r in got if r.conv_id == 99) == [(0, 1000), (1, 1000), (2, 500)]
    assert len({(r.conv_id, r.part) for r in got}) == len(got) == 43
