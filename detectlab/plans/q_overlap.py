"""Deduplication and decontamination over runs of 20 tokens."""

from __future__ import annotations

from pyspark.sql import functions as F

from detectlab.functions.tokens import TOKENS_SQL, tokens
from detectlab.operators import overlap
from detectlab.plans.registry import Registry
from detectlab.sources.tables import cut, load

R = Registry()


def _toks(table: str, key: str) -> str:
    return f"SELECT {key} AS id, {TOKENS_SQL.format('text')} AS t FROM {table}"


def _grams(name: str, table: str, key: str) -> str:
    return f"{name} AS (SELECT DISTINCT id, array_to_string(t[p:p + 19], ' ') AS g FROM (SELECT id, t, unnest(range(1, len(t) - 18)) AS p FROM ({_toks(table, key)})))"


D, B = _grams("d", "documents", "doc_id"), _grams("b", "benchmark", "item_id")
_PAIRS = f"{D}, {B}, pair AS (SELECT DISTINCT d.id AS doc_id, b.id AS item_id FROM d JOIN b USING (g))"


def _tables(spark, sf):
    return load(spark, sf, "documents").select("doc_id", "text"), load(spark, sf, "benchmark")


def _pairs(spark, sf, strategy="grams"):
    docs, bench = _tables(spark, sf)
    return overlap.overlap_pairs(docs, bench, a_id="doc_id", b_id="item_id", strategy=strategy)


@R.query(f"SELECT lang, count(*) AS docs, sum(len(t))::BIGINT AS tokens, max(len(t))::INT AS longest, count(*) FILTER (len(t) >= 20) AS long_enough FROM ({_toks('documents', 'lang, doc_id')}) GROUP BY lang")
def token_stats(spark, sf):
    n = F.size(tokens("text"))
    return load(spark, sf, "documents").select("lang", n.alias("n")).groupBy("lang").agg(F.count("*").alias("docs"), F.sum("n").alias("tokens"), F.max("n").alias("longest"), F.count_if(F.col("n") >= 20).alias("long_enough"))


@R.query(f"WITH {D}, {B} SELECT 'documents' AS side, count(*) AS rows, count(DISTINCT id) AS ids, count(DISTINCT g) AS grams FROM d UNION ALL SELECT 'benchmark', count(*), count(DISTINCT id), count(DISTINCT g) FROM b")
def ngram_counts(spark, sf):
    docs, bench = _tables(spark, sf)
    count = lambda df, i, side: overlap.distinct_grams(df, i, "text").agg(F.count("*").alias("rows"), F.countDistinct("id").alias("ids"), F.countDistinct("h").alias("grams")).select(F.lit(side).alias("side"), "*")
    return count(docs, "doc_id", "documents").union(count(bench, "item_id", "benchmark"))


@R.query(f"WITH {_PAIRS} SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM pair)")
def decontaminate(spark, sf):
    docs, bench = _tables(spark, sf)
    return overlap.decontaminate(docs, bench, train_id="doc_id", test_id="item_id").select("doc_id")


@R.query(f"WITH {_PAIRS} SELECT item_id FROM benchmark WHERE item_id NOT IN (SELECT item_id FROM pair)")
def decontaminate_test_side(spark, sf):
    docs, bench = _tables(spark, sf)
    return overlap.decontaminate(docs, bench, train_id="doc_id", test_id="item_id", drop="test").select("item_id")


@R.query(f"WITH {_PAIRS} SELECT 'train' AS side, doc_id AS id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM pair) UNION ALL SELECT 'test', item_id FROM benchmark WHERE item_id NOT IN (SELECT item_id FROM pair)")
def decontaminate_both(spark, sf):
    docs, bench = _tables(spark, sf)
    return overlap.decontaminate(docs, bench, train_id="doc_id", test_id="item_id", drop="both")


@R.query(f"WITH {_PAIRS} SELECT * FROM pair")
def contaminated_pairs(spark, sf):
    return _pairs(spark, sf)


@R.query(f"WITH {_PAIRS} SELECT * FROM pair")
def contaminated_pairs_winnow(spark, sf):
    return _pairs(spark, sf, "winnow")


_FIRST = f"{D}, low AS (SELECT g, min(id) AS first FROM d GROUP BY g), gone AS (SELECT DISTINCT id FROM d JOIN low USING (g) WHERE id > first)"


@R.query(f"WITH {_FIRST} SELECT doc_id AS id, doc_id NOT IN (SELECT id FROM gone) AS kept FROM documents")
def dedup_first(spark, sf):
    return overlap.dedup(_tables(spark, sf)[0], "doc_id", "text", "first")


_EDGES = f"{D}, low AS (SELECT g, min(id) AS first FROM d GROUP BY g), e AS (SELECT DISTINCT id, first FROM d JOIN low USING (g) WHERE id > first), s AS (SELECT id AS x, first AS y FROM e UNION SELECT first, id FROM e)"


@R.query(f"WITH RECURSIVE {_EDGES}, reach(x, y) AS (SELECT x, x FROM s UNION SELECT r.x, s.y FROM reach r JOIN s ON s.x = r.y), c AS (SELECT x AS id, min(y) AS component FROM reach GROUP BY x) SELECT doc_id AS id, component IS NULL OR component = doc_id AS kept FROM documents LEFT JOIN c ON c.id = doc_id")
def dedup_component(spark, sf):
    return overlap.dedup(_tables(spark, sf)[0], "doc_id", "text", "component")


_WITHIN = "{0}low AS (SELECT g, min(id) AS first FROM {0} GROUP BY g), {0}gone AS (SELECT DISTINCT id FROM {0} JOIN {0}low USING (g) WHERE id > first)"


@R.query(f"""WITH {_PAIRS}, r AS (SELECT * FROM d WHERE id NOT IN (SELECT doc_id FROM pair)), {_WITHIN.format('r')}, {_WITHIN.format('b')}
SELECT 'train' AS side, doc_id AS id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM pair) AND doc_id NOT IN (SELECT id FROM rgone)
UNION ALL SELECT 'test', item_id FROM benchmark WHERE item_id NOT IN (SELECT id FROM bgone)""")
def decontaminate_chain(spark, sf):
    """Between the sets, then within train, then within test."""
    docs, bench = _tables(spark, sf)
    train, test = overlap.decontaminate_chain(docs, bench, train_id="doc_id", test_id="item_id")
    return train.select(F.lit("train").alias("side"), F.col("doc_id").alias("id")).union(test.select(F.lit("test").alias("side"), F.col("item_id").alias("id")))


@R.query()
def dedup_greedy(spark, sf):
    return overlap.dedup(_tables(spark, sf)[0], "doc_id", "text", "greedy")


@R.query("SELECT min(doc_id) AS doc_id, count(*) AS copies FROM documents GROUP BY text")
def exact_dedup(spark, sf):
    return overlap.exact_dedup(_tables(spark, sf)[0], "doc_id", "text")


@R.query(f"""WITH {_PAIRS},
dp AS (SELECT id AS doc_id, p, array_to_string(t[p:p + 19], ' ') AS g FROM (SELECT id, t, unnest(range(1, len(t) - 18)) AS p FROM ({_toks('documents', 'doc_id')})) WHERE id IN (SELECT doc_id FROM pair)),
bp AS (SELECT id AS item_id, p AS q, array_to_string(t[p:p + 19], ' ') AS g FROM (SELECT id, t, unnest(range(1, len(t) - 18)) AS p FROM ({_toks('benchmark', 'item_id')}))),
h AS (SELECT doc_id, item_id, p, p - q AS dg, p - row_number() OVER (PARTITION BY doc_id, item_id, p - q ORDER BY p) AS i FROM dp JOIN bp USING (g))
SELECT doc_id, item_id, max(m) + 19 AS tokens FROM (SELECT doc_id, item_id, dg, i, count(*) AS m FROM h GROUP BY ALL) GROUP BY doc_id, item_id""")
def longest_run(spark, sf):
    docs, bench = _tables(spark, sf)
    return overlap.longest_run(cut(_pairs(spark, sf)), docs, bench, a_id="doc_id", b_id="item_id")


@R.query(f"""WITH {_FIRST.replace('low AS', 'low0 AS').replace('JOIN low USING', 'JOIN low0 USING')}, {B}, pair AS (SELECT DISTINCT d.id AS doc_id, b.id AS item_id FROM d JOIN b USING (g))
SELECT (SELECT count(*) FROM documents) AS docs, (SELECT count(*) FROM pair) AS pairs, (SELECT count(DISTINCT doc_id) FROM pair) AS contaminated, (SELECT count(DISTINCT item_id) FROM pair) AS items_hit, (SELECT count(*) FROM gone) AS repeated""")
def overlap_report(spark, sf):
    docs, _ = _tables(spark, sf)
    pairs = cut(_pairs(spark, sf)).agg(F.count("*").alias("pairs"), F.countDistinct("doc_id").alias("contaminated"), F.countDistinct("item_id").alias("items_hit"))
    gone = overlap.dedup(docs, "doc_id", "text", "first").agg(F.count("*").alias("docs"), F.count_if(~F.col("kept")).alias("repeated"))
    return gone.crossJoin(pairs).select("docs", "pairs", "contaminated", "items_hit", "repeated")  # one row each
