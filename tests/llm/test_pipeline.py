import duckdb

import corpus_pipeline
from detectlab.llm.decontam import Search
from detectlab.llm.mixing import targets
from detectlab.llm.queries import OP1_SQL
from tests.llm.test_decontam import edit
from tests.llm.test_jaccard import brute
from tests.llm.test_lines_quality_mixing import WORD, brute_lines

SF = "/root/testdata/sf0.001"


def words(text):
    import re

    return re.findall(r"[0-9A-Za-z\u0080-\U0010ffff]+", text.lower())


def test_each_stage_equals_brute_force(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = {r.doc_id: r for r in docs.collect()}
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{SF}/documents.parquet'")
    texts = {i: rows[i].text for (i,) in con.execute(f"SELECT doc_id FROM ({OP1_SQL}) WHERE kept").fetchall()}

    one = corpus_pipeline.quality_rules(spark, docs, SF)
    assert one.columns == docs.columns and {r.doc_id: r.text for r in one.collect()} == texts

    two = corpus_pipeline.line_dedup(spark, one, SF)
    texts = {i: t for i, t, _ in brute_lines(sorted(texts.items()))}
    got = two.collect()
    assert two.columns == docs.columns and {r.doc_id: r.text for r in got} == texts
    assert all(r.n_chars == len(r.text) for r in got if r.text != rows[r.doc_id].text)

    three = corpus_pipeline.near_duplicates(spark, spark.createDataFrame(got, docs.schema), SF)
    texts = {i: texts[i] for i, _, c in brute(sorted(texts.items()), 5, 80) if i == c}
    got = three.collect()
    assert three.columns == docs.columns and {r.doc_id: r.text for r in got} == texts

    four = corpus_pipeline.decontaminate(spark, spark.createDataFrame(got, docs.schema), SF)
    items = [words(r.text) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    how = Search()
    hit = {i for i, t in texts.items() if any(len(set(w) & set(words(t))) >= 0.5 * len(set(w)) and edit(w, words(t)) <= how.edits(len(w)) for w in items)}
    got = four.collect()
    assert four.columns == docs.columns and {r.doc_id for r in got} == set(texts) - hit

    left = {r.doc_id: (r.source, len(WORD.findall(r.text))) for r in got}
    five = corpus_pipeline.mix_sources(spark, spark.createDataFrame(got, docs.schema), SF)
    size = {}
    for s, n in left.values():
        size[s] = size.get(s, 0) + n
    order = sorted(size)
    goal = dict(zip(order, targets([size[s] for s in order], [1 + k % 3 for k in range(len(order))])))
    taken = dict.fromkeys(order, 0)
    for r in five.collect():
        assert 0 < r.taken <= 3 * r.size == 3 * left[r.doc_id][1]
        taken[r.source] += r.taken
    assert all(abs(taken[s] - goal[s]) <= 64 + 0.03 * goal[s] for s in order)


def test_run(spark):
    out = corpus_pipeline.run(spark, SF)
    assert out.count() > 20 and set(spark.read.parquet(f"{SF}/documents.parquet").columns) < set(out.columns)
