"""Brute force for queries without a DuckDB form, and edges of the later operators."""

import re

import pytest
from pyspark.sql import functions as F

from detectlab.functions import respond
from detectlab.functions.tokens import gram_hashes, tokens, winnow
from detectlab.operators import overlap as O
from detectlab.plans import q_more, q_ops, q_overlap

SF = "/root/testdata/sf0.001"


def texts(spark, key="doc_id", table="documents"):
    return {r[0]: r[1] for r in spark.read.parquet(f"{SF}/{table}.parquet").select(key, "text").collect()}


def words(text):
    return re.findall("[0-9a-zà-öø-ÿ]+", (text or "").lower())


def runs(text, n=20):
    w = words(text)
    return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)}


@pytest.mark.parametrize("n", [1, 2, 3, 5, 20])
def test_gram_hashes_tell_grams_apart(spark, n):
    rows = [(1, list("abcabcd")), (2, []), (3, ["x"]), (4, list("abcdefghijklmnopqrstuvwxyz") * 2), (5, None)]
    g3 = gram_hashes(F.col("t"), 3)
    for r in spark.createDataFrame(rows, "id int, t array<string>").select("t", gram_hashes(F.col("t"), n).alias("g"), g3.alias("g3"), winnow(g3, n).alias("w")).collect():
        t = r.t or []
        grams = [tuple(t[i : i + n]) for i in range(len(t) - n + 1)]
        assert len(grams) == len(r.g) and len(set(grams)) == len(set(r.g)) == len(set(zip(grams, r.g)))
        least = [min(r.g3[i : i + n]) for i in range(len(r.g3) - n + 1)] or ([min(r.g3)] if r.g3 else [])
        assert list(dict.fromkeys(least)) == r.w


def test_greedy_by_brute_force(spark):
    kept, seen = set(), set()
    for i, t in sorted(texts(spark).items()):
        if not (g := runs(t)) & seen:
            kept.add(i)
            seen |= g
    assert {r.id for r in q_overlap.dedup_greedy(spark, SF).collect() if r.kept} == kept


def test_fingerprints_lose_no_run(spark):
    """Rows one token short, exactly long enough, null and empty, and a run at either end."""
    run = [f"w{i}" for i in range(20)]
    rows = [(1, " ".join(["a", "b", *run])), (2, " ".join([*run, "c"])), (3, " ".join(run[1:])), (4, None), (5, ""), (6, " ".join(run))]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert {r.id for r in O.dedup(df, "doc_id", "text").collect() if r.kept} == {1, 3, 4, 5}
    train, test = O.decontaminate_chain(df, df.where("doc_id in (4, 6)").withColumnRenamed("doc_id", "item_id"), train_id="doc_id", test_id="item_id")
    assert {r.doc_id for r in train.collect()} == {3, 4, 5} and {r.item_id for r in test.collect()} == {4, 6}


def test_minhash_recall(spark):
    sets = {i: set(words(t)) for i, t in texts(spark).items()}
    ids = sorted(i for i, s in sets.items() if s)
    near = {(a, b) for k, a in enumerate(ids) for b in ids[k + 1 :] if len(sets[a] & sets[b]) > 0.9 * len(sets[a] | sets[b])}
    got = {(r.a, r.b) for r in q_ops.op_minhash_lsh(spark, SF).collect()}
    assert near and len(near & got) >= 0.9 * len(near)
    assert all(len(sets[a] & sets[b]) >= 0.899 * len(sets[a] | sets[b]) for a, b in got)


def test_batch_answers(spark):
    df = spark.createDataFrame([(i, f"p{i}" if i % 3 else None) for i in range(200)], "k long, prompt string")
    sizes = lambda prompts: [f"{p}:{len(prompts) <= 7}" for p in prompts]
    got = {r.k: r.answer for r in respond.batch_answers(df, sizes, "k", size=7).collect()}
    assert got == {i: f"{f'p{i}' if i % 3 else None}:True" for i in range(200)}
    assert respond.batch_answers(df.limit(0), sizes, "k").count() == 0
    with pytest.raises(Exception, match="2 prompts, 0 answers"):
        respond.batch_answers(df.limit(2).coalesce(1), lambda prompts: [], "k").count()


def test_stored_answers_keep_unanswered(spark):
    prompts = spark.createDataFrame([(1,), (2,)], "k long")
    answers = spark.createDataFrame([(1, "m", "x"), (1, "m", "y"), (2, "other", "z")], "k long, model string, answer string")
    got = sorted((r.k, r.answer or "") for r in respond.stored_answers(prompts, answers, "k", "m").collect())
    assert got == [(1, "x"), (1, "y"), (2, "")]


def test_more_queries_are_registered():
    assert set(q_more.R.queries) == set(q_more.R.oracles)
