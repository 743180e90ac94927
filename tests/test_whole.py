"""Queries do the whole job: against DuckDB forms without the cuts, hand-made tables, and brute force."""

import pytest

from detectlab import plans
from detectlab.operators import baselines as B
from detectlab.operators import generate as G
from detectlab.operators import project as P
from detectlab.sources import tables
from detectlab.sources.tables import fix_patches, patch_sql, samples
from tests import oracle

SF = "/root/testdata/sf0.001"
QUERIES, ORACLES = plans.collect()


@pytest.fixture(scope="module")
def con():
    return oracle.connect(SF)


def test_every_urgent_order_is_a_fix(spark, con):
    want = con.execute("SELECT count(DISTINCT o_orderkey) FROM orders JOIN customer ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey WHERE o_orderpriority = '1-URGENT'").fetchone()[0]
    assert fix_patches(spark, SF).select("vuln_id").distinct().count() == want > fix_patches(spark, SF, sparse=True).select("vuln_id").distinct().count()


@pytest.mark.parametrize("name", ["project_score", "project_compare", "vuln_hits", "false_flags", "unknown_findings", "ablate_agent", "project_scenarios", "fuzz_budget", "fuzz_confirmed", "bounded_flow"])
def test_whole_fixes(spark, con, name):
    whole = ORACLES[name].replace(patch_sql(True), patch_sql(False))
    assert "% 50" not in whole
    oracle.compare(QUERIES[name](spark, SF), con, whole)


@pytest.mark.parametrize("name", ["assemble_snippet", "lookup_tool", "reachable_cyclic"])
def test_whole_inputs(spark, con, name):
    whole = ORACLES[name].replace(patch_sql(True), patch_sql(False)).replace("depth < 8", "depth < 20")
    for cut in ("o_orderkey % 200 = 0 AND ", " AND l_orderkey % 97 = 0", " WHERE l_orderkey % 50 = 0", " WHERE l_orderkey % 5 = 0"):
        whole = whole.replace(cut, "")
    assert " = 0" not in whole
    oracle.compare(QUERIES[name](spark, SF), con, whole)


def test_a_long_cycle_is_walked_to_its_end(spark, tmp_path):
    rows = [(1, k, k) for k in range(1, 36)] + [(1, k + 1, k) for k in range(1, 35)]  # s1 - p1 - s2 - ... - s35 - p35
    spark.createDataFrame(rows, "l_orderkey long, l_suppkey long, l_partkey long").coalesce(1).write.parquet(f"{tmp_path}/lineitem.parquet")
    got = {r.node: r.depth for r in QUERIES["reachable_cyclic"](spark, str(tmp_path)).collect()}
    assert got == {f"s{k}": 2 * k - 2 for k in range(1, 36)} | {f"p{k}": 2 * k - 1 for k in range(1, 36)}


def test_shots_are_the_nearest_of_the_language(spark):
    df = samples(spark, "/root/testdata/sf0.01", labelled=True)
    rows = df.select("sample_id", "lang", "n_tokens", "split").collect()
    want = {q.sample_id: [i for _, i in sorted((abs(b.n_tokens - q.n_tokens), b.sample_id) for b in rows if b.split == "train" and b.lang == q.lang)[:3]] for q in rows if q.split == "test"}
    got = {r.sample_id: r.shots for r in QUERIES["few_shots"](spark, "/root/testdata/sf0.01").collect()}
    assert got == want and [] in got.values()


def test_shots_of_ties_and_of_few(spark):
    make = lambda rows: spark.createDataFrame(rows, "sample_id long, lang string, n_tokens int")
    pool = make([(k, "a", 200) for k in range(9, 0, -1)] + [(20, "a", 198), (21, "a", 199), (30, "b", 7)])
    got = {r.sample_id: r.shots for r in G.pick_shots(make([(100, "a", 199), (101, "a", 200), (102, "a", 1), (103, "b", 900), (104, "c", 1), (105, None, 1)]), pool).collect()}
    assert got == {100: [21, 1, 2], 101: [1, 2, 3], 102: [20, 21, 1], 103: [30], 104: [], 105: []}


def test_a_planted_leak_is_found(spark, monkeypatch):
    train = spark.createDataFrame([(1, "a"), (2, "b"), (3, "b"), (5, "c"), (6, None)], "sample_id long, project string")
    assert P.project_leak_check(train, spark.createDataFrame([("b",), ("b",), ("d",), (None,)], "project string")).first().leaked == 2
    assert QUERIES["project_leak"](spark, SF).first().leaked == 0
    monkeypatch.setattr(tables, "OOD_CLASSES", (16, 17, 18, 19))  # the split lets src15 into training
    assert QUERIES["project_leak"](spark, SF).first().leaked == samples(spark, SF).where("split = 'train' AND cls = 15").count() > 0


@pytest.mark.parametrize("most", [1_000, 10])
def test_rules_past_the_500th(spark, monkeypatch, most):
    monkeypatch.setattr(B, "RULE_ROWS", most)
    text = lambda k: f"word{k:04d}"
    train = [(k, " ".join(text(w) for w in range(600)), 7, True) for k in (1, 2)] + [(3, "fine", 7, False)]
    test = [(10, text(599), 7, True), (11, "fine", 7, False), (12, f"{text(3)} {text(598)}", 7, True)]
    make = lambda rows: spark.createDataFrame(rows, "sample_id long, code string, cls int, is_vuln boolean")
    rules = B.learn_rules(make(train))
    assert rules.count() == 600
    assert {r.sample_id: (r.verdict, r.word) for r in B.rule_scan(make(test), rules).collect()} == {10: ("CWE-7", text(599)), 11: ("benign", None), 12: ("CWE-7", text(3))}
    assert {r.sample_id: r.flagged for r in B.guard_scan(make(test), rules).collect()} == {10: True, 11: False, 12: True}


def test_classes_of_test_rows_are_never_read(spark):
    s = samples(spark, "/root/testdata/sf0.01", labelled=True)
    train, test = s.where("split = 'train'"), s.where("split = 'test'")
    other = test.selectExpr("*", "'CWE-99' AS x").drop("cwe", "cls").withColumnRenamed("x", "cwe").selectExpr("*", "99 AS cls")
    learned, model = B.learn_structure(train), B.fit_student(train)
    for scan in (lambda d: B.structure_scan(d, learned), lambda d: B.student_predict(model, d)):
        got = {r.sample_id: r.verdict for r in scan(test).collect()}
        assert got == {r.sample_id: r.verdict for r in scan(other).collect()} and "CWE-99" not in got.values()
        assert len(set(got.values())) > 1
