"""The answer of the machines against a plain reading of their weights, text by text."""

import math

import pyarrow as pa

from detectlab.llm.langid import SCALE, count_grams, fit, identify


def plain(model, text):
    """Family with the greatest margin, then the language of it with the most pairwise wins (then the greatest sum of margins)."""
    if not text or not any(c.isalpha() for c in text):
        return "und"
    counts = [int(c) for c in count_grams(pa.array([text]))[0]]
    total = sum(counts)
    if not total:
        return model.common
    margin = lambda m: (sum(c * int(m[0][g]) for g, c in enumerate(counts) if c) / total + m[1]) / SCALE
    names = sorted(model.languages)
    family = max(names, key=lambda f: margin(model.family[f])) if len(names) > 1 else names[0]
    langs = model.languages[family]
    votes, sums = dict.fromkeys(langs, 0), dict.fromkeys(langs, 0.0)
    for (a, b), m in model.pair.items():
        if a in votes and b in votes:
            d = margin(m)
            votes[a if d > 0 else b] += 1
            sums[a] += d
            sums[b] -= d
    return max(langs, key=lambda x: votes[x] + 1e-6 * math.tanh(sums[x]))


def test_votes_equal_plain_reading(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text", "lang")
    model = fit(docs)
    rows = {r.doc_id: r.text for r in docs.collect()}
    got = {r.doc_id: r.lang_pred for r in identify(docs, model).collect()}
    assert got == {i: plain(model, t) for i, t in rows.items()}


def test_three_languages_of_a_family(spark):
    """Three machines vote; a text of words that all have in common is still read the same way."""
    words = {"es": "casa perro gato mesa libro", "pt": "cachorro janela livro cadeira mulher", "it": "cane gatto finestra libro donna"}
    rows = [(k * 10 + n, " ".join(w.split()[(n + j) % 5] for j in range(9)), c) for k, (c, w) in enumerate(words.items()) for n in range(8)] + [(900, "libro livro casa cane", None), (901, "7 8", None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = fit(docs)
    got = {r.doc_id: r.lang_pred for r in identify(docs, model).collect()}
    assert got == {i: plain(model, t) for i, t, _ in rows}
