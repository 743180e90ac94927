import zlib

from detectlab.llm.langid import fit, identify


def test_accuracy_on_rows_not_learned(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    truth = {r.doc_id: (r.lang, r.text) for r in docs.collect()}
    got = identify(docs).collect()
    assert len(got) == len(truth)
    test = [r for r in got if r.held_out]
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) and 0 <= r.score <= 1 for r in got)
    right = sum(r.lang_pred == truth[r.doc_id][0] for r in test if r.lang_pred != "und")
    assert right >= 0.97 * len(test)
    again = {r.doc_id: (r.lang_pred, r.score) for r in identify(docs.repartition(13)).collect()}
    assert again == {r.doc_id: (r.lang_pred, r.score) for r in got}


def test_labels_of_held_out_rows_are_not_used(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text", "lang")
    wrong = docs.selectExpr("doc_id", "text", "case when crc32(cast(doc_id as string)) % 4 = 2 then 'xx' else lang end as lang")
    a, b = fit(docs), fit(wrong)
    assert a.languages == b.languages and all((a.family[f][0] == b.family[f][0]).all() for f in a.family)


def test_odd_rows(spark):
    rows = [(1, "the house and the garden of the king", "en"), (3, "der Hund und die Katze im Haus", "de"), (4, "le chat et la maison de la reine", "fr"), (5, None, "en"), (6, "123 ...", None), (7, "é", None), (None, "the king", "zz"), (8, "", None), (8, "", None), (9, "x" * 200000, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string").selectExpr("*", "1 as score")
    got = {r.doc_id: r for r in identify(df).collect()}
    assert got[5].lang_pred == got[6].lang_pred == got[8].lang_pred == "und" and got[6].score == 0
    assert got[7].lang_pred in {"en", "de", "fr"} and got[None].held_out is False
    assert all(r.lang_pred != "zz" for r in got.values())
    assert identify(df.limit(0)).count() == 0
    assert {r.lang_pred for r in identify(df.selectExpr("doc_id", "text", "cast(null as string) lang")).collect()} == {"und"}
