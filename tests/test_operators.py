"""Hand-made cases with answers written by hand, invariants, and brute force."""

import math
import random

import pytest
from pyspark.sql import functions as F

from detectlab.functions import simulate
from detectlab.operators import baselines as B
from detectlab.operators import generate as G
from detectlab.operators import graph as GR
from detectlab.operators import infer as I
from detectlab.operators import metrics as M
from detectlab.operators import overlap as O
from detectlab.operators import prefs as P
from detectlab.operators import project as PR
from detectlab.sources.tables import samples

SF = "/root/testdata/sf0.001"


def run(n, tag):
    return [f"{tag}{k}" for k in range(n)]


def text_rows(spark, rows, key="doc_id"):
    return spark.createDataFrame([(i, " ".join(w)) for i, w in rows], f"{key} long, text string")


CHAIN = [(1, run(25, "a")), (2, run(25, "a")[:20] + run(25, "b")), (3, run(25, "b")[5:] + ["z"])]
FORK = [(1, run(22, "a")), (2, run(22, "b")), (3, run(22, "a") + run(22, "b"))]


@pytest.mark.parametrize("rows,mode,kept", [(CHAIN, "first", {1}), (CHAIN, "component", {1}), (CHAIN, "greedy", {1, 3}), (FORK, "first", {1, 2}), (FORK, "component", {1}), (FORK, "greedy", {1, 2})])
def test_three_meanings_of_dedup(spark, rows, mode, kept):
    got = O.dedup(text_rows(spark, rows), "doc_id", "text", mode)
    assert {r.id for r in got.collect() if r.kept} == kept


def test_19_and_20_tokens(spark):
    a = text_rows(spark, [(1, ["x"] + run(19, "s") + ["y"]), (2, ["x"] + run(20, "s") + ["y"]), (3, ["short"])])
    b = text_rows(spark, [(9, ["p"] + run(20, "s") + ["q"])], "item_id")
    for strategy in ("grams", "winnow"):
        got = O.overlap_pairs(a, b, a_id="doc_id", b_id="item_id", strategy=strategy).collect()
        assert [(r.doc_id, r.item_id) for r in got] == [(2, 9)]
    clean = O.decontaminate(a, b, train_id="doc_id", test_id="item_id")
    assert {r.doc_id for r in clean.collect()} == {1, 3}
    assert O.overlap_pairs(clean, b, a_id="doc_id", b_id="item_id").count() == 0


def test_pairs_equal_brute_force(spark):
    rnd = random.Random(1)
    pool = [run(30, f"p{k}x") for k in range(8)]
    make = lambda: [w for _ in range(rnd.randint(1, 3)) for w in rnd.choice(pool)[rnd.randint(0, 12) :]]
    left, right = [(i, make()) for i in range(30)], [(i, make()) for i in range(20)]
    grams = lambda w: {tuple(w[k : k + 20]) for k in range(len(w) - 19)}
    want = {(i, j) for i, a in left for j, b in right if grams(a) & grams(b)}
    for strategy in ("grams", "winnow"):
        got = O.overlap_pairs(text_rows(spark, left), text_rows(spark, right, "item_id"), a_id="doc_id", b_id="item_id", strategy=strategy)
        assert {(r.doc_id, r.item_id) for r in got.collect()} == want
    once = O.dedup(text_rows(spark, left), "doc_id", "text").where("kept").collect()
    kept = [(i, w) for i, w in left if i in {r.id for r in once}]
    assert all(r.kept for r in O.dedup(text_rows(spark, kept), "doc_id", "text").collect())


def answers(spark, rows):
    return spark.createDataFrame(rows, "sample_id long, model string, attempt int, out_tokens int, total_tokens int, verdict string, is_vuln boolean, cls int, hinted boolean, n_tokens int, cwe string")


def answer(s, a, out, total, verdict, vuln=True, cls=7):
    return (s, "T1", a, out, total, verdict, vuln, cls, False, total - out, f"CWE-{cls}")


def test_rejection_and_length_cut(spark):
    rows = [answer(1, 1, 900, 1000, "CWE-7"), answer(1, 2, 400, 500, "CWE-7"), answer(1, 3, 100, 200, "benign"), answer(1, 4, 50, 32_001, "CWE-7"), answer(2, 1, 5, 32_000, "CWE-7"), answer(3, 1, 5, 9, None), answer(3, 2, 5, 9, "CWE-1")]
    a = answers(spark, rows)
    assert {(r.sample_id, r.attempt) for r in G.reject(a).collect()} == {(1, 2), (2, 1)}
    assert {(r.sample_id, r.attempt) for r in G.reject(a, inclusive=True).collect()} == {(1, 2)}
    assert [r.sample_id for r in G.unsolved(a).collect()] == [3]
    totals = {t: G.length_filter(answers(spark, [answer(1, 1, 5, t, "CWE-7")])).count() for t in (31_999, 32_000, 32_001)}
    assert totals == {31_999: 1, 32_000: 1, 32_001: 0}


def test_corrected_rows_are_new_and_unhinted(spark):
    s = samples(spark, SF, labelled=True)
    log = G.respond(s)
    first, extra = G.reject(log), G.correct(s, log, G.hints(spark))
    assert G.hints(spark).count() == 73 and G.hints(spark).select("cwe").distinct().count() == 19
    assert first.join(extra, "sample_id", "left_semi").count() == 0 and extra.count() > 0
    assert G.stage1(first, extra, s).where("prompt LIKE '%For class%'").count() == 0


def test_majority_ties_go_to_the_first(spark):
    votes = spark.createDataFrame([(1, k + 1, v) for k, v in enumerate("ABBACCCC")], "sample_id int, attempt int, answer string")
    assert {r.k: r.answer for r in I.majority(votes, (1, 4, 8)).collect()} == {1: "A", 4: "A", 8: "C"}


def test_policy(spark):
    rows = [(1, "m", k + 1, c, s) for k, (c, s) in enumerate([(3, 3), (3, 5), (9, 9), (3, 3)])] + [(2, "m", k, 19, 19) for k in range(1, 5)]
    got = {r.sample_id: r for r in I.policy(spark.createDataFrame(rows, "sample_id int, model string, attempt int, claim int, second int")).collect()}
    assert got[1].policy == ["CWE-3", "CWE-5", "CWE-9"] and not got[1].padded
    assert got[2].policy == ["CWE-19", "CWE-0"] and got[2].padded


def test_advantages(spark):
    rows = [(1, "m", r) for r in (1.0, 1.0, 1.0, 1.0)] + [(2, "m", r) for r in (1.0, 0.0, 0.0, -1.0)]
    got = P.group_advantage(spark.createDataFrame(rows, "sample_id int, model string, reward double")).collect()
    assert all(r.advantage == 0 for r in got if r.sample_id == 1)
    two = [r.advantage for r in got if r.sample_id == 2]
    assert sum(two) == pytest.approx(0) and max(two) == pytest.approx(math.sqrt(2))


@pytest.mark.parametrize("mode,want", [("strict", (0, 0, 1, 0)), ("double", (0, 1, 1, 0)), ("binary", (1, 0, 0, 0))])
def test_a_wrong_class(spark, mode, want):
    p = spark.createDataFrame([("m", True, 119, "CWE-416")], "model string, is_vuln boolean, cls int, verdict string")
    r = M.confusion(p, mode=mode).first()
    assert (r.tp, r.fp, r.fn, r.tn) == want


def test_cells_sum_to_rows(spark):
    p = G.respond(samples(spark, SF, labelled=True), tuple(simulate.MODELS), 1)
    n = p.count()
    assert sum(r.tp + r.fp + r.fn + r.tn for r in M.confusion(p).collect()) == n
    s = M.rates(M.confusion(p)).collect()
    assert all(x is None or 0 <= x <= 1 for r in s for x in (r.precision, r.recall, r.f1, r.fpr, r.fnr))


EDGES = [("e", "a"), ("a", "t"), ("e", "b"), ("b", "t"), ("e", "t"), ("t", "a")]


def test_paths_of_a_cyclic_graph(spark):
    e, entry = spark.createDataFrame(EDGES, "src string, dst string"), spark.createDataFrame([("e",)], "entry string")
    t = spark.createDataFrame([("t",)], "node string")
    assert {tuple(r.path) for r in GR.simple_paths(e, entry, t).collect()} == {("e", "t"), ("e", "a", "t"), ("e", "b", "t")}
    lv = GR.level_counts(e, entry, layered=True)
    assert [(r.paths, r.shortest) for r in GR.path_counts(lv, t).collect()] == [(1, 1)]
    assert {r.node: r.depth for r in GR.reachable(e, entry).collect()} == {"e": 0, "a": 1, "b": 1, "t": 1}
    with pytest.raises(ValueError):
        GR.level_counts(e, entry, max_depth=6)


def test_sampled_paths_are_paths(spark):
    rnd = random.Random(2)
    edges = sorted({(f"n{a}", f"n{b}") for a in range(40) for b in rnd.sample(range(a + 1, 45), min(4, 44 - a))})
    e, entry = spark.createDataFrame(edges, "src string, dst string"), spark.createDataFrame([("n0",)], "entry string")
    t = spark.createDataFrame([(f"n{k}",) for k in range(30, 45)], "node string")
    lv = GR.level_counts(e, entry, max_depth=45)
    total = {r.target: int(r.paths) for r in GR.path_counts(lv, t).collect()}
    got = {}
    for r in GR.sample_paths(e, lv, t).collect():
        assert r.path[0] == "n0" and r.path[-1] == r.target and all(p in set(edges) for p in zip(r.path, r.path[1:]))
        got.setdefault(r.target, set()).add(tuple(r.path))
    assert {k: len(v) for k, v in got.items()} == {k: min(3, n) for k, n in total.items()}


def test_indirect_edges_need_the_same_signature(spark):
    f = spark.createDataFrame([("f", 1, ["int"], True, False), ("g", 2, ["int", "char"], True, False), ("h", 2, ["char", "int"], True, False), ("s", 2, ["int", "char"], False, True)], "fn_id string, arity int, param_types array<string>, address_taken boolean, pointer_site boolean")
    assert [(r.src, r.dst) for r in GR.indirect_edges(f, materialise=True).collect()] == [("s", "g")]
    hop = GR.indirect_edges(f)
    two = hop.alias("x").join(hop.alias("y"), F.col("x.dst") == F.col("y.src")).select("x.src", "y.dst").collect()
    assert [tuple(r) for r in two] == [("s", "g")]


def test_fix_rule(spark):
    patch = spark.createDataFrame([("P", 1, "p"), ("P", 1, "q")], "project string, vuln_id int, fn_id string")
    flags = spark.createDataFrame([("P", "q", "t"), ("P", "r", "t")], "project string, fn_id string, tool string")
    assert PR.vuln_hits(flags, patch).first().found
    assert [r.fn_id for r in PR.false_flags(flags, patch).collect()] == ["r"]


def test_merged_classes(spark):
    df = spark.createDataFrame([(f"CWE-{k}",) for k in (125, 787, 119, 415, 416, 476, 190)], "cwe string")
    assert df.select(PR.merge_classes("cwe").alias("m")).distinct().count() == 4
    assert len(PR.SCOPE["java"]) == 13


def test_masks_and_histories(spark):
    rows = [(1, k, r, f"t{k}") for k, r in enumerate(["system", "user", "assistant", "user", "assistant"])]
    turns = spark.createDataFrame(rows, "conv_id int, turn int, role string, text string")
    assert [m.learn for m in P.loss_mask(turns).first().messages] == [False, False, True, False, True]
    got = P.turn_examples(turns).orderBy("turn").collect()
    assert [(len(r.history), r.target) for r in got] == [(2, "t2"), (4, "t4")]


def test_extended_rules_flag_more(spark):
    s = samples(spark, "/root/testdata/sf0.01", labelled=True)
    train, test = s.where("split = 'train'"), s.where("split = 'test'")
    few, many = (B.rule_scan(test, B.learn_rules(train, support=k)).where("verdict <> 'benign'").select("sample_id") for k in (3, 2))
    assert few.exceptAll(many).count() == 0


def test_parsing_takes_the_last_section(spark):
    rows = [("x Final Answer: benign y Final Answer: vulnerable CWE-1, CWE-2", "vulnerable", ["CWE-1", "CWE-2"], True), ("Final Answer: benign", "benign", [], True), ("CWE-5", None, [], False), ("Final Answer: vulnerable", "vulnerable", [], False)]
    got = G.parse_answer(spark.createDataFrame([(r[0],) for r in rows], "chain string")).collect()
    assert [(r.said, r.said_classes, r.said_well) for r in got] == [r[1:] for r in rows]
