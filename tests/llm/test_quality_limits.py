"""Limits come from the corpus: other habits, other limits."""

import random

import pytest

from detectlab.llm.quality import Rules, cut, limits, quantiles, sketches, verdicts, with_counts


def text(rnd, symbols=0.0, n=120):
    return " ".join("".join(rnd.choice("abcdefghij") for _ in range(rnd.randint(2, 8))) + ("##$" if rnd.random() < symbols else "") for _ in range(n))


@pytest.fixture(scope="module")
def groups(spark):
    """prose has no symbols, code has some in every text; one text of each has symbols in most words."""
    rnd = random.Random(5)
    rows = [(i, text(rnd), "en", "prose") for i in range(150)] + [(1000 + i, text(rnd, rnd.uniform(0.3, 0.5)), "en", "code") for i in range(150)]
    rows += [(500, text(rnd, 0.3), "en", "prose"), (1500, text(rnd, 1.0), "en", "code")]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").cache()


def test_other_habits_other_limits(groups):
    got = {r.doc_id: r.kept for r in verdicts(groups).select("doc.doc_id", "kept").collect()}
    assert not got[500] and sum(got[i] for i in range(150)) == 150  # a share that is usual in code is not in prose
    assert sum(got[1000 + i] for i in range(150)) == 150
    counted = with_counts(groups).selectExpr("doc.lang", "doc.source", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines")
    found = limits(cut(quantiles(sketches(counted, Rules()), Rules())), Rules()).where("level = 0").collect()
    high = {r.source_key: r.symbol_share.high for r in found}
    assert high["=prose"] == 0 < high["=code"]


def test_a_group_of_copies_keeps_other_texts(spark):
    rnd = random.Random(6)
    copy = text(rnd)
    rows = [(i, copy, "en", "a") for i in range(400)] + [(1000 + i, text(rnd), "en", "a") for i in range(60)] + [(2000 + i + 300 * (s == "c"), text(rnd), "en", s) for i in range(300) for s in ("b", "c")] + [(3000, "x" * 40 + " " + " ".join("y" * 30 + str(k) for k in range(80)), "en", "a")]
    got = {r.doc_id: r.kept for r in verdicts(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")).select("doc.doc_id", "kept").collect()}
    assert not got.pop(3000) and all(got.values())


def test_ties_and_one_document(spark):
    """Quantiles that tie are the limit, and what equals it is kept."""
    same = spark.createDataFrame([(i, text(random.Random(7)), None, None) for i in range(5)], "doc_id long, text string, lang string, source string")
    assert verdicts(same).where("kept").count() == 5
    assert verdicts(same.limit(1)).where("kept").count() == 1
    assert verdicts(same.limit(0)).count() == 0
