import hashlib
import random
import re

from detectlab.llm.substring import COVERS, mark_repeats

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def brute(rows, n=13):
    words = [(i, WORD.findall(t or "")) for i, t in rows]
    least = {}
    for i, w in words:
        if i is not None:
            for k in range(len(w) - n + 1):
                key = tuple(w[k : k + n])
                least[key] = min(least.get(key, i), i)
    out = []
    for i, w in words:
        gone = set()
        if i is not None:
            for k in range(len(w) - n + 1):
                if least[tuple(w[k : k + n])] < i:
                    gone.update(range(k, k + n))
        kept = " ".join(x for k, x in enumerate(w) if k not in gone)
        out.append((i, len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest()))
    return out


def order(rows):
    return sorted(rows, key=lambda r: tuple((x is None, x) for x in r))


def test_covers_meet():
    for v, d in COVERS.items():
        for a in range(v):
            for b in range(v):
                assert any((a + s) % v in d and (b + s) % v in d for s in range(v))


def test_equals_brute_force(spark):
    rnd = random.Random(3)
    vocab = ["a", "bb", "ccc", "é", "日本", "x" * 40]
    passages = [[rnd.choice(vocab) for _ in range(rnd.randint(10, 40))] for _ in range(6)]
    rows = [(None, None), (5, None), (6, ""), (7, "  \n"), (None, " ".join(passages[0] * 2))]
    for i in range(120):
        w = []
        for _ in range(rnd.randint(0, 5)):
            p = rnd.choice(passages)
            a = rnd.randint(0, 8)
            w += [str(rnd.random())[:5] for _ in range(rnd.randint(0, 9))] + p[a:]
        rows.append((rnd.randint(0, 200), rnd.choice([" ", "\n", "\t "]).join(w)))
    rows += rows[-3:]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumnsRenamed({})
    got = mark_repeats(df.selectExpr("*", "1 as n_words", "2 as `to`")).drop("kept_text")
    assert order([tuple(r) for r in got.collect()]) == order(brute(rows))


def test_empty_table(spark):
    assert mark_repeats(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_short_and_long_texts(spark):
    long = " ".join(str(k) for k in range(60000))
    rows = [(1, long), (2, "0 1 2 3 4 5 6 7 8 9 10 11 12"), (3, "0 1 2"), (4, "z" * 300000 + " " + long)]
    got = {r.doc_id: r for r in mark_repeats(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert [got[i].n_removed for i in (1, 2, 3, 4)] == [0, 13, 0, 60000]
