"""Queries on the training-corpus operators: one opN_<name> each, over whole tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from detectlab.llm import chat, decontam, jaccard, langid, lines, mixing, pii, quality, substring, warc
from detectlab.llm.frames import documents


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir).select("doc_id", "text", "lang", "source")
    return quality.verdicts(docs).select("doc.doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op2_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per document and benchmark item found in it."""
    return decontam.matches(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def op3_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir).select("doc_id", "text", "source")
    return mixing.takes(docs).select("doc_id", "size", "source_size", "target", "taken")


def op4_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.classes(documents(spark, sf_dir), jaccard.Join(words=3, percent=90))


def op5_pii_crf(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.digest(pii.find(documents(spark, sf_dir)))


def op6_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir).select("doc_id", "text")
    return lines.dedup_lines(docs).select("doc.doc_id", "n_lines", "n_removed", F.sha2("doc.text", 256).alias("text_sha256"))


def op7_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.identify(documents(spark, sf_dir).select("doc_id", "text", "lang"))


def op8_warc_zstd(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, records = warc.archive(spark.read.parquet(f"{sf_dir}/pages.parquet"), min_bytes=0)
    return records.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op9_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Turns written as plain transcripts, and what the model makes of these; conversations of 1,000 turns and more have a row a part."""
    turns = spark.read.parquet(f"{sf_dir}/conversations.parquet")
    plain = chat.transcripts_of(turns)
    out = chat.parse(plain, chat.fit(plain))
    return out.select("conv_id", "part", "n_turns", F.array_join("roles", ",").alias("roles"), F.sha2("chat", 256).alias("chat_sha256"))


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring.mark_repeats(documents(spark, sf_dir), window=13).select("doc_id", "n_words", "n_removed", "kept_sha256")


QUERIES = {f.__name__: f for f in (op1_quality_rules, op2_decontaminate, op3_mix_sources, op4_ngram_jaccard, op5_pii_crf, op6_line_dedup, op7_language_id, op8_warc_zstd, op9_chat_format, op10_substring_dedup)}

_WORD = r"[^\x20\x09-\x0D]+"

#: Base counts and the verdict of the quality rules, by exact grouping on the sketch's bins.
OP1_SQL = rf"""
WITH w AS (
  SELECT doc_id, lang, source, coalesce(text, '') AS text, regexp_extract_all(coalesce(text, ''), '{_WORD}') AS ws FROM documents),
win AS (
  SELECT doc_id, p, ws[p] || ' ' || ws[p + 1] || ' ' || ws[p + 2] AS g
  FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 1)) AS p FROM w)),
twice AS (SELECT doc_id, g FROM win GROUP BY ALL HAVING count(*) > 1),
rep AS (
  SELECT doc_id, count(DISTINCT p + k) AS n_repeat_words FROM win JOIN twice USING (doc_id, g), (VALUES (0), (1), (2)) v(k) GROUP BY doc_id),
ln AS (
  SELECT doc_id, count(*) AS n_lines, count(*) - count(DISTINCT line) AS n_dup_lines
  FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM w) WHERE regexp_matches(line, '{_WORD}') GROUP BY doc_id),
c AS (
  SELECT w.doc_id, coalesce('=' || lang, '-') AS lang_key, coalesce('=' || source, '-') AS source_key,
    len(ws)::BIGINT AS n_words, length(regexp_replace(text, '[\x20\x09-\x0D]', '', 'g'))::BIGINT AS word_chars,
    length(regexp_replace(text, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
    coalesce(n_dup_lines, 0)::BIGINT AS n_dup_lines, coalesce(n_repeat_words, 0)::BIGINT AS n_repeat_words, coalesce(n_lines, 0)::BIGINT AS n_lines
  FROM w LEFT JOIN rep USING (doc_id) LEFT JOIN ln USING (doc_id)),
f AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM c),
h AS (
  SELECT *, greatest(n_symbols - ceil(3 * sqrt(n_symbols))::BIGINT, 0) AS symbols, greatest(n_dup_lines - ceil(3 * sqrt(n_dup_lines))::BIGINT, 0) AS dups,
    greatest(n_repeat_words - ceil(3 * sqrt(n_repeat_words))::BIGINT, 0) AS repeats FROM f),
m AS (
  SELECT doc_id, lang_key, source_key, base_failed, unnest([
    {{'measure': 'symbol_share', 'v': 10000 * symbols // greatest(word_chars, 1)}}, {{'measure': 'dup_line_share', 'v': 10000 * dups // greatest(n_lines, 1)}},
    {{'measure': 'repeat_share', 'v': 10000 * repeats // greatest(n_words, 1)}}, {{'measure': 'word_length', 'v': 10000 * word_chars // greatest(n_words, 1)}}], recursive := true)
  FROM h),
b AS (SELECT *, greatest(length(bin(v)) - 8, 0) AS e FROM m),
s AS (
  SELECT level, CASE WHEN level < 2 THEN lang_key ELSE '' END AS lk, CASE WHEN level < 1 THEN source_key ELSE '' END AS sk, measure, e * 128 + (v >> e) AS bin, count(*) AS docs
  FROM b, (VALUES (0), (1), (2)) l(level) WHERE NOT base_failed GROUP BY ALL),
r AS (SELECT *, sum(docs) OVER (PARTITION BY level, lk, sk, measure ORDER BY bin) AS seen, sum(docs) OVER (PARTITION BY level, lk, sk, measure) AS n,
    CASE WHEN bin < 256 THEN bin ELSE (bin % 128 + 128) << (bin // 128 - 1)::INT END AS low,
    CASE WHEN bin < 255 THEN bin ELSE (((bin + 1) % 128 + 128) << ((bin + 1) // 128 - 1)::INT) - 1 END AS top FROM s),
fence(measure, q_low, q_high, reach) AS (VALUES ('symbol_share', 25, 75, 3), ('dup_line_share', 50, 90, 3), ('repeat_share', 50, 99, 3), ('word_length', 25, 75, 5)),
q AS (
  SELECT level, lk, sk, measure, reach, max(n) AS n, min(low) FILTER (seen * 100 >= n * q_low) AS lo, min(top) FILTER (seen * 100 >= n * q_high) AS hi
  FROM r JOIN fence USING (measure) GROUP BY level, lk, sk, measure, reach),
usual AS (SELECT * FROM q WHERE level = 0 AND n >= 100),
wide AS (
  SELECT q.*, reach * greatest(q.hi - q.lo, of_lang, of_all) AS width
  FROM q LEFT JOIN (SELECT lk, measure, quantile_disc(hi - lo, 0.5) * 50 // 100 AS of_lang FROM usual GROUP BY lk, measure) USING (lk, measure)
    LEFT JOIN (SELECT measure, quantile_disc(hi - lo, 0.5) * 50 // 100 AS of_all FROM usual GROUP BY measure) USING (measure)),
lim AS (
  SELECT level, lk, sk, measure, hi + width AS high, CASE WHEN measure = 'word_length' THEN lo - width ELSE -1 END AS low
  FROM wide WHERE level = 2 OR n >= 100),
fit AS (
  SELECT doc_id, bool_and(coalesce(v BETWEEN coalesce(a.low, g.low, h.low) AND coalesce(a.high, g.high, h.high), true)) AS fits
  FROM b LEFT JOIN lim a ON a.level = 0 AND a.lk = lang_key AND a.sk = source_key AND a.measure = b.measure
    LEFT JOIN lim g ON g.level = 1 AND g.lk = lang_key AND g.measure = b.measure LEFT JOIN lim h ON h.level = 2 AND h.measure = b.measure
  GROUP BY doc_id)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND fits AS kept FROM f JOIN fit USING (doc_id)
"""

OP6_SQL = rf"""
WITH l AS (SELECT doc_id, text, string_split(text, chr(10)) AS ls FROM documents),
win AS (
  SELECT doc_id, p, ls[p + 1] || chr(10) || ls[p + 2] || chr(10) || ls[p + 3] AS g FROM (SELECT doc_id, ls, unnest(range(0, len(ls) - 2)) AS p FROM l)
  WHERE regexp_matches(ls[p + 1] || chr(10) || ls[p + 2] || chr(10) || ls[p + 3], '{_WORD}')),
later AS (SELECT doc_id, p FROM (SELECT *, row_number() OVER (PARTITION BY g ORDER BY doc_id, p) AS n FROM win) WHERE n > 1),
gone AS (SELECT DISTINCT doc_id, p + k AS line FROM later, (VALUES (0), (1), (2)) v(k)),
parts AS (
  SELECT e.doc_id, string_agg(ls[p + 1], chr(10) ORDER BY p) FILTER (g.line IS NULL) AS kept, count(g.line) AS n_removed
  FROM (SELECT doc_id, ls, unnest(range(0, len(ls))) AS p FROM l) e LEFT JOIN gone g ON g.doc_id = e.doc_id AND g.line = e.p GROUP BY e.doc_id)
SELECT l.doc_id, coalesce(len(ls), 0)::BIGINT AS n_lines, coalesce(n_removed, 0)::BIGINT AS n_removed,
  CASE WHEN text IS NULL THEN NULL ELSE sha256(coalesce(kept, '')) END AS text_sha256
FROM l LEFT JOIN parts USING (doc_id)
"""

OP4_SQL = rf"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{_WORD}') AS ws FROM documents),
s AS (
  SELECT DISTINCT doc_id, hash(g) AS g FROM (
    SELECT doc_id, unnest(list_transform(range(1, len(ws) - 1), lambda p: ws[p:p + 2])) AS g FROM w WHERE len(ws) >= 3
    UNION ALL SELECT doc_id, ws FROM w WHERE len(ws) BETWEEN 1 AND 2)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
meet AS (
  SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS k FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
link AS (SELECT x, y FROM meet JOIN n p ON p.doc_id = x JOIN n q ON q.doc_id = y WHERE 100 * k >= 90 * (p.n + q.n - k)),
sym AS (SELECT x, y FROM link UNION SELECT y, x FROM link),
reach(x, y) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.x, sym.y FROM reach r JOIN sym ON sym.x = r.y)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, min(r.y)::BIGINT AS component_id
FROM documents d LEFT JOIN n USING (doc_id) JOIN reach r ON r.x = d.doc_id GROUP BY d.doc_id, n.n
"""

ORACLES: dict[str, str] = {"op1_quality_rules": OP1_SQL, "op4_ngram_jaccard": OP4_SQL, "op6_line_dedup": OP6_SQL}
