"""Speakers by what comes again in a transcript, in styles and names that are not learned; Viterbi against enumeration."""

import itertools

import numpy as np
import pytest

from detectlab.llm import chat


@pytest.fixture(scope="module")
def model(spark):
    return chat.fit(chat.transcripts_of(spark.read.parquet("/root/testdata/sf0.01/conversations.parquet")))


def test_unknown_names(model):
    talk = [(1, "hello?"), (2, "good day.\nmore of it."), (1, "what is new?"), (2, "little.")]
    for form in ("{}: {}", "**{}:** {}", "[{}] {}", "{}> {}"):
        text = "\n".join(form.format("Alice" if r == 1 else "Bob", t) for r, t in talk)
        assert chat.turns_of(text, model) == talk, form
    one = "User: a?\nMarvin: so it is.\nUser: b?\nMarvin: and so on."
    assert chat.turns_of(one, model) == [(1, "a?"), (2, "so it is."), (1, "b?"), (2, "and so on.")]


def test_words_that_look_like_names_stay_in_the_text(model):
    text = "User: how much?\nAssistant: let me see.\nAnswer: 42\nContext: none\nUser: sure?\nAssistant: yes.\nNote: twice.\nNote: checked."
    assert chat.turns_of(text, model) == [(1, "how much?"), (2, "let me see.\nAnswer: 42\nContext: none"), (1, "sure?"), (2, "yes.\nNote: twice.\nNote: checked.")]


@pytest.mark.parametrize("form", ["USER: {}|BOT: {}", "<user> {}|<assistant> {}", "## Human:\n{}|## AI:\n{}", "Customer> {}|Agent> {}", "[Human]: {}|[Assistant]: {}"])
def test_styles_not_learned(spark, model, form):
    turns = spark.read.parquet("/root/testdata/sf0.01/conversations.parquet").where("role <> 'system'").orderBy("conv_id", "turn").collect()
    right = total = 0
    for _, own in itertools.groupby(turns, key=lambda r: r.conv_id):
        talk = [({"user": 1, "assistant": 2}[r.role], r.text.strip()) for r in own if r.text and r.text.strip()]
        text = "\n".join(form.split("|")[r - 1].format(t) for r, t in talk)
        got = chat.turns_of(text, model)
        total += len(talk)
        right += len(talk) if got == talk else sum(a == b for a, b in zip(got, talk)) if len(got) == len(talk) else 0
    assert total > 100 and right >= 0.9 * total, (right, total)


def test_viterbi_equals_enumeration(model):
    rnd = np.random.default_rng(1)
    for _ in range(20):
        marks, shapes = rnd.integers(0, chat.N_MARKS, 4), rnd.integers(0, chat.N_SHAPES, 4)
        score = lambda p: model.start[p[0]] + sum(model.step[a, b] for a, b in zip(p, p[1:])) + sum(model.mark[s, m] + model.look[s, x] for s, m, x in zip(p, marks, shapes))
        best = max(itertools.product(range(len(chat.STATES)), repeat=4), key=score)
        assert score(tuple(model.viterbi(marks, shapes).tolist())) == pytest.approx(score(best))
