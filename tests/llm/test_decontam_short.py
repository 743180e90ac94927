import random

from detectlab.llm.decontam import Search, matches
from tests.llm.test_decontam import change, edit


def test_short_items_are_searched_up_to_20_percent(spark):
    rnd = random.Random(4)
    items = [(i, [f"i{i}w{k}" for k in range(rnd.randint(5, 11))]) for i in range(30)]
    docs = [(0, items[0][1][:2] + ["x"] + items[0][1][3:])]
    for d in range(1, 300):
        w = [f"p{rnd.randint(0, 99)}" for _ in range(rnd.randint(0, 30))]
        at = rnd.randint(0, len(w))
        w[at:at] = change(rnd, rnd.choice(items)[1], rnd.randint(0, 3))
        docs.append((d, w))
    # a middle word of five
    items.append((99, "one two three four five".split()))
    docs += [(900, "one two other four five".split()), (901, "so one two four five".split()), (902, "one two new three four five".split()), (903, "one other three new five".split())]
    make = lambda rows, key: spark.createDataFrame([(i, " ".join(w)) for i, w in rows], f"{key} long, text string")
    got = {(r.doc_id, r.item_id): r.edits for r in matches(make(docs, "doc_id"), make(items, "item_id")).collect()}
    near = {(d, i): (edit(t, w), len(t)) for d, w in docs for i, t in items}
    want = {k: e for k, (e, size) in near.items() if e <= size * 20 // 100}
    assert all((d, 99) in got for d in (900, 901, 902)) and (903, 99) not in got
    assert all(want.get(k) == e for k, e in got.items()) and len(got) >= 0.99 * len(want) and len(want) > 100
    assert [Search().gram(n) for n in (5, 6, 10, 15)] == [2, 3, 3, 3]
