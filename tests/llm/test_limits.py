"""Past former limits: long tokens, texts beside others, many languages, shuffled joins."""

import itertools
import time

import numpy as np

from detectlab.llm import langid, lines, pii, warc


def plain_nodes(text):
    import re

    return [m.span() for m in re.finditer(r"[^\x20\x09-\x0D]+", text) if re.search("[0-9@]", m[0])]


def test_tokens_with_digits():
    for bits in itertools.product(["a", "1", " ", "\n", "@b", "\x0b"], repeat=5):
        text = "".join(bits)
        assert list(pii.active_tokens(text)) == plain_nodes(text)


def test_a_long_token_is_read_once():
    began = time.time()
    for text in ("a" * 1_000_000, "a" * 1_000_000 + "1", "Zm9v" * 250_000 + " 12345678", "x1 " * 100_000):
        pii.graph_of([text], [pii.base_spans(text)])
    assert time.time() - began < 20


def field(k=len(pii.KINDS) + 1):
    rnd = np.random.default_rng(3)
    own = {c: rnd.normal(size=k) for c in range(40)}
    near, far = rnd.normal(size=(k, k)), rnd.normal(size=(k, k)) + 2 * np.eye(k)
    return pii.Field(own, near + near.T, far + far.T, np.zeros(k))


def test_messages_equal_enumeration_where_there_is_no_loop():
    f, k = field(), len(pii.KINDS) + 1
    g = pii.Graph([0] * 4, [(0, 1)] * 4, [1, 2, 3, 4], [0, 2, 0, 0], [0] * 4, [(0, 1), (1, 2)], [(2, 3)])
    share = np.zeros((4, k))
    for labels in itertools.product(range(k), repeat=4):
        if labels[1] == 2:
            weight = np.exp(sum(f.own[c][x] for n, (c, x) in enumerate(zip(g.code, labels)) if n != 1) + sum(f.near[labels[a], labels[b]] for a, b in g.near) + sum(f.far[labels[a], labels[b]] for a, b in g.far))
            share[range(4), labels] += weight
    assert np.abs(f.infer(g, rounds=200) - share / share.sum(1, keepdims=True)).max() < 1e-3


def test_spans_do_not_depend_on_the_texts_beside(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    texts, f = [r.text for r in docs.select("text").collect()], pii.fit(docs)
    together = pii.add_spans(texts, f, 0.5)[1]
    assert together == [pii.add_spans([t], f, 0.5)[1][0] for t in texts]


def test_seventy_languages(spark):
    rows = [(n * 100 + k, f"{chr(97 + n % 26)}{chr(97 + n // 26)}" * 3 + f" w{chr(97 + n % 26)}{chr(98 + n // 26)}x yes", f"l{n:02d}") for n in range(70) for k in range(6)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = langid.fit(docs)
    assert sum(map(len, model.languages.values())) == 70
    got = {r.doc_id: r.lang_pred for r in langid.identify(docs, model).collect()}
    assert sum(got[i] == lang for i, _, lang in rows) > 0.95 * len(rows)
    assert all(len(p) == 1 for p in langid.fit(docs, most_rows=10).languages.values())


def test_few_letters_get_the_most_frequent_language(spark):
    rows = [(k, "le chat et la maison de la reine", "fr") for k in range(40)] + [(100 + k, "the house and the garden", "en") for k in range(8)] + [(900, "é", None)]
    got = langid.identify(spark.createDataFrame(rows, "doc_id long, text string, lang string")).where("doc_id = 900").first()
    assert got.lang_pred == "fr"


def test_shuffled_joins_give_the_same(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    view = lambda df: sorted((r.at_id, r.at_row, tuple(sorted(r.covered))) for r in df.collect())
    assert view(lines.repeated_lines(docs)) == view(lines.repeated_lines(docs, broadcast_rows=-1)) != []
    pages = spark.createDataFrame([(k, f"u{k}", "same" if k % 3 else f"own {k}") for k in range(60)] + [(None, "u", "same")], "page_id long, url string, html string")
    plan = lambda **how: sorted(map(tuple, warc.plan_records(pages, **how).collect()), key=repr)
    assert plan() == plan(broadcast_rows=-1) and sum(r[3] == 1 for r in plan()) == 40
