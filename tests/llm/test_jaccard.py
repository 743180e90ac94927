import random
import re

import pytest

from detectlab.llm.components import components
from detectlab.llm.jaccard import Join, classes, keep_one

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def lower(t):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t)


def brute(rows, w, pct):
    sets = []
    for i, t in rows:
        ws = WORD.findall(lower(t or ""))
        sets.append({tuple(ws[k : k + w]) for k in range(len(ws) - w + 1)} if len(ws) >= w else ({tuple(ws)} if ws else set()))
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            k = len(sets[a] & sets[b])
            if k and 100 * k >= pct * (len(sets[a]) + len(sets[b]) - k):
                root[find(a)] = find(b)
    out = []
    for a in range(len(rows)):
        ids = [rows[b][0] for b in range(len(rows)) if find(b) == find(a) and rows[b][0] is not None]
        out.append((rows[a][0], len(sets[a]), min(ids) if ids else None))
    return out


def order(rows):
    return sorted(rows, key=lambda r: tuple((x is None, x) for x in r))


def corpus(rnd):
    rows = [(None, None), (900, ""), (901, " \n"), (902, "one two"), (903, "ONE two"), (None, "one two"), (None, "nobody else has this"), (905, "é É é ß x")]
    common = [f"c{k}" for k in range(30)]
    nxt = iter(range(1, 800))
    for size in (9, 10, 11, 12, 20, 21, 40, 60, 120, 200):
        for _ in range(3):
            base = [f"w{rnd.randint(0, 9999)}" for _ in range(size)]
            for _ in range(rnd.randint(1, 6)):
                t = list(base)
                for _ in range(rnd.choice([0, 0, 1, 1, 2, 3])):
                    t[rnd.randrange(len(t))] = f"n{rnd.randint(0, 9999)}"
                if rnd.random() < 0.3:
                    t = t + [f"tail{rnd.randint(0, 9)}"]
                if rnd.random() < 0.3:
                    t = common + t
                rows.append((next(nxt), " ".join(t)))
    return rows + rows[-4:]


@pytest.mark.parametrize("w,pct", [(3, 90), (5, 80), (1, 50)])
def test_equals_brute_force(spark, w, pct):
    rows = corpus(random.Random(w))
    random.Random(1).shuffle(rows)
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "'x' as node", "1 as n")
    for how in (Join(words=w, percent=pct), Join(words=w, percent=pct, frequent=0, light_cap=1), Join(words=w, percent=pct, list_run=2)):
        got = [tuple(r) for r in classes(df, how).collect()]
        assert order(got) == order(brute(rows, w, pct))


def test_keep_one(spark):
    rows = [(3, "a b c d e f"), (1, "a b c d e f"), (1, "a b c d e f"), (2, "other words stand here now"), (None, "a b c d e f"), (4, None)]
    kept = keep_one(spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 as gone"))
    assert kept.columns == ["doc_id", "text", "gone"]
    assert order([(r.doc_id, r.text) for r in kept.collect()]) == order([rows[1], rows[3], rows[4], rows[5]])


def test_empty(spark):
    df = spark.createDataFrame([], "doc_id long, text string")
    assert classes(df).count() == 0
    assert keep_one(df).count() == 0


def test_components_of_chains_and_stars(spark):
    rnd = random.Random(5)
    edges = [(i, i + 1) for i in range(500)] + [(1000, k) for k in range(1001, 1200)] + [(rnd.randint(2000, 2100), rnd.randint(2000, 2100)) for _ in range(60)] + [(7, 7), (None, 3)]
    rnd.shuffle(edges)
    df = spark.createDataFrame(edges, "a long, b long").repartition(7)
    got = {r.node: r.root for r in components(df, small=0).collect()}
    assert got == {r.node: r.root for r in components(df).collect()}
    near = {}
    for a, b in edges:
        if a is not None and a != b:
            near.setdefault(a, set()).add(b)
            near.setdefault(b, set()).add(a)
    want = {}
    for n in sorted(near):
        if n not in want:
            todo = [n]
            while todo:
                x = todo.pop()
                if x not in want:
                    want[x] = n
                    todo += near[x]
    assert got == want
