import random

import numpy as np

from detectlab.llm.decontam import Items, Search, best_edits, matches, without_matches


def edit(a, b):
    """Fewest edits from a to any run of b."""
    row = [0] * (len(b) + 1)
    for x in a:
        new = [row[0] + 1]
        for k, y in enumerate(b):
            new.append(min(row[k] + (x != y), row[k + 1] + 1, new[-1] + 1))
        row = new
    return min(row)


def test_best_edits():
    rnd = random.Random(2)
    for _ in range(200):
        a = [rnd.randint(0, 3) for _ in range(rnd.randint(1, 9))]
        b = [rnd.randint(0, 3) for _ in range(rnd.randint(0, 12))]
        a, b = [x + 1 for x in a], [x + 1 for x in b]
        assert best_edits(np.array([a], np.uint64), np.array([b + [0, 0]], np.uint64))[0] == edit(a, b)


def change(rnd, words, k):
    w = list(words)
    for _ in range(k):
        p = rnd.randrange(len(w))
        kind = rnd.random()
        if kind < 0.4:
            w[p] = f"sub{rnd.randint(0, 999)}"
        elif kind < 0.7:
            w.insert(p, f"ins{rnd.randint(0, 999)}")
        else:
            del w[p]
    return w


def corpus(seed):
    rnd = random.Random(seed)
    vocab = ["the", "of", "and", "à", "in"] + [f"w{k}" for k in range(400)]
    prose = lambda n: [rnd.choice(vocab[:5]) if rnd.random() < 0.4 else rnd.choice(vocab) for _ in range(n)]
    items = [(i, prose(rnd.randint(5, 60))) for i in range(40)]
    docs = []
    for d in range(300):
        w = prose(rnd.randint(0, 200))
        if d % 3 == 0:
            i, t = rnd.choice(items)
            at = rnd.randint(0, len(w))
            w[at:at] = change(rnd, t, rnd.randint(0, Search().edits(len(t)) + 2))
        docs.append((d, w))
    return items, docs


def test_finds_what_brute_force_finds(spark):
    found = want = 0
    for seed in range(3):
        items, docs = corpus(seed)
        text = lambda w: ", ".join(w).upper() + "."
        df = spark.createDataFrame([(d, text(w)) for d, w in docs], "doc_id long, text string")
        bench = spark.createDataFrame([(i, " ".join(w)) for i, w in items], "item_id long, text string")
        got = {(r.doc_id, r.item_id): r.edits for r in matches(df, bench).collect()}
        true = {}
        for d, w in docs:
            for i, t in items:
                e = edit(t, w)
                if e <= Search().edits(len(t)):
                    true[d, i] = e
        assert set(got) <= set(true)
        assert all(got[k] == true[k] for k in got)
        found, want = found + len(got), want + len(true)
        clean = {r.doc_id for r in without_matches(df, bench).collect()}
        assert clean == {d for d, _ in docs} - {d for d, _ in got}
        blocks = {(r.doc_id, r.item_id) for r in matches(df, bench, Search(block_words=300)).collect()}
        assert blocks == set(got)
    assert want > 150 and found >= 0.99 * want


def test_odd_rows(spark):
    item = "one two three four five six seven eight"
    bench = spark.createDataFrame([(1, item), (2, None), (3, ""), (4, "one two"), (None, item), (1, item)], "item_id long, text string")
    rows = [(None, f"x {item} y", 1), (5, None, 2), (6, "", 3), (7, item, 4), (7, item, 4), (8, "zz " * 200000 + item, 5), (9, "q" * 200000, 6)]
    df = spark.createDataFrame(rows, "doc_id long, text string, item_id int")
    got = sorted(((r.doc_id, r.item_id, r.edits) for r in matches(df, bench).collect()), key=repr)
    assert got == sorted([(None, 1, 0), (7, 1, 0), (7, 1, 0), (8, 1, 0)], key=repr)
    assert sorted(r.doc_id for r in without_matches(df, bench).collect()) == [5, 6, 9]
    assert matches(df.limit(0), bench).count() == 0 and matches(df, bench.limit(0)).count() == 0
    assert without_matches(df, bench.limit(0)).count() == len(rows)
    assert Items([], Search()).ids == []
