"""Streams, sinks, Python functions and the rarer built-in operators, each on a given table."""

from __future__ import annotations

import uuid

import pandas as pd
import pyarrow as pa
from pyspark.sql import functions as F

from detectlab.functions import respond
from detectlab.plans.q_ops import _folder
from detectlab.plans.registry import Registry
from detectlab.sources import sinks
from detectlab.sources.tables import SAMPLE_SQL, load, samples
from detectlab.streaming import streams

R = Registry()
#: Longer than any table's time span: nothing of a finished table counts as late.
NEVER = "36500 days"


def _stream(spark, sf, columns=("event_id", "ts", "user_id", "event_type", "value"), copies: int = 1):
    """The events as a stream of files, and a folder for the checkpoint; copies: times that each file comes."""
    path = f"{_folder(spark)}/events"
    events = load(spark, sf, "events").select(*columns)
    for _ in range(copies):
        events.write.mode("append").parquet(path)
    return streams.event_time(streams.file_stream(spark, path, events.schema, files=1000)), f"{path}-checkpoint"


@R.query("SELECT event_type, time_bucket(INTERVAL 30 MINUTE, ts) - k * INTERVAL 30 MINUTE AS start, count(*) AS n FROM events, (VALUES (0), (1)) v(k) GROUP BY ALL")
def op_stream_sliding(spark, sf):
    """Windows of an hour, one each half hour."""
    s, checkpoint = _stream(spark, sf)
    out = streams.run_once(streams.tumbling(s, "1 hour", slide="30 minutes"), f"sliding_{uuid.uuid4().hex}", checkpoint, "complete")
    return out.select("event_type", F.col("window.start").cast("timestamp_ntz").alias("start"), "n")


@R.query("""WITH e AS (SELECT user_id, ts, coalesce(ts - lag(ts) OVER w > INTERVAL 3 HOUR, true) AS opens FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, count(*) FILTER (opens) OVER (PARTITION BY user_id ORDER BY ts) AS no FROM e)
SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, no""")
def op_stream_sessions(spark, sf):
    """Runs of a user's events with at most three hours between them."""
    s, checkpoint = _stream(spark, sf, ("ts", "user_id"))
    out = streams.run_to_files(streams.bursts(s, "3 hours"), f"{checkpoint}-out", checkpoint, "complete")
    return out.select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("start"), "n")


@R.query("SELECT event_id, user_id FROM events")
def op_stream_dedup(spark, sf):
    """Every event comes twice and goes on once."""
    s, checkpoint = _stream(spark, sf, ("event_id", "ts", "user_id"), copies=2)
    out = streams.run_to_files(streams.first_seen(s, "event_id", NEVER).select("event_id", "user_id"), f"{checkpoint}-out", checkpoint)
    return out.select("event_id", "user_id")


@R.query("SELECT p.event_id AS prompt, a.event_id AS answer FROM events p JOIN events a ON a.user_id = p.user_id AND a.ts BETWEEN p.ts AND p.ts + INTERVAL 1 HOUR WHERE p.event_type = 'click' AND a.event_type = 'purchase'")
def op_stream_join(spark, sf):
    """Clicks with the purchases of the same user in the hour after them, both as streams."""
    s, checkpoint = _stream(spark, sf)
    prompts = s.where("event_type = 'click'").select(F.col("user_id").alias("prompt_id"), F.col("ts").alias("asked_at"), F.col("event_id").alias("prompt"))
    answers = s.where("event_type = 'purchase'").select(F.col("user_id").alias("answer_to"), F.col("ts").alias("answered_at"), F.col("event_id").alias("answer"))
    out = streams.run_once(streams.answered(prompts, answers, "1 hour", NEVER), f"join_{uuid.uuid4().hex}", checkpoint)
    return out.select("prompt", "answer")


@R.query(f"WITH {SAMPLE_SQL} SELECT split, lang, count(*) AS n, sum(n_tokens)::BIGINT AS tokens FROM sample GROUP BY split, lang")
def op_sink_samples(spark, sf):
    """Files by split and language, read again: both columns come from the folders' names."""
    path = f"{_folder(spark)}/samples"
    sinks.write_samples(samples(spark, sf), path)
    return spark.read.parquet(path).groupBy("split", "lang").agg(F.count("*").alias("n"), F.sum("n_tokens").alias("tokens"))


@R.query("SELECT conv_id * 1000000 + turn AS key, role, length(text) AS chars FROM conversations")
def op_sink_shards(spark, sf):
    """Records as JSON lines in the order of a key, read again."""
    path = f"{_folder(spark)}/shards"
    sinks.write_shards(load(spark, sf, "conversations").select((F.col("conv_id") * 1000000 + F.col("turn")).alias("key"), "role", "text"), path)
    return spark.read.schema("key long, role string, text string").json(path).select("key", "role", F.length("text").cast("long").alias("chars"))


@R.query("SELECT length(regexp_replace(text, '[^aeiou]', '', 'g')) AS vowels, doc_id FROM documents")
def op_pandas_udf(spark, sf):
    @F.pandas_udf("long")
    def vowels(text: pd.Series) -> pd.Series:
        return text.str.count("[aeiou]").astype("Int64")

    return load(spark, sf, "documents").select("doc_id", vowels("text").alias("vowels"))


@R.query("SELECT u.user_id, count(DISTINCT c.event_id) AS clicks, count(DISTINCT p.event_id) AS purchases FROM (SELECT DISTINCT user_id FROM events WHERE event_type IN ('click', 'purchase')) u LEFT JOIN events c ON c.user_id = u.user_id AND c.event_type = 'click' LEFT JOIN events p ON p.user_id = u.user_id AND p.event_type = 'purchase' GROUP BY u.user_id")
def op_cogroup(spark, sf):
    """Two sides of a user met in one call; either may be empty."""

    def meet(key: tuple, a: pa.Table, b: pa.Table) -> pa.Table:
        return pa.table({"user_id": pa.array([key[0].as_py()], pa.int64()), "clicks": pa.array([a.num_rows], pa.int64()), "purchases": pa.array([b.num_rows], pa.int64())})

    side = lambda kind: load(spark, sf, "events").where(F.col("event_type") == kind).select("user_id", "event_id").groupBy("user_id")
    return side("click").cogroup(side("purchase")).applyInArrow(meet, "user_id long, clicks long, purchases long")


@R.query("SELECT event_type, quantile_disc(value, 0.9) AS p90, true AS near, string_agg(DISTINCT user_id % 10, ',' ORDER BY user_id % 10) AS digits FROM events GROUP BY event_type")
def op_approximate(spark, sf):
    """Sketched quantile (exact below its accuracy) and count (within a tenth of the exact one), and a list in order."""
    digit = (F.col("user_id") % 10).cast("string")
    near = F.abs(F.approx_count_distinct("user_id", 0.02) - F.countDistinct("user_id")) * 10 <= F.countDistinct("user_id")
    return load(spark, sf, "events").groupBy("event_type").agg(F.percentile_approx("value", 0.9, 10_000_000).alias("p90"), near.alias("near"), F.array_join(F.array_sort(F.collect_set(digit)), ",").alias("digits"))


@R.query("SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def op_grouping_sets(spark, sf):
    d = load(spark, sf, "documents")
    return d.groupingSets([["lang"], ["source"], []], "lang", "source").agg(F.count("*").alias("n")).select("lang", "source", "n")


@R.query("SELECT lang, source, count(*) AS n FROM documents GROUP BY CUBE (lang, source)")
def op_cube(spark, sf):
    return load(spark, sf, "documents").cube("lang", "source").agg(F.count("*").alias("n"))


@R.query("SELECT count(*) AS n, 0::BIGINT AS in_both, (SELECT count(*) FROM events WHERE event_type IN ('click', 'error')) AS chosen FROM events")
def op_splits(spark, sf):
    """A random split loses no row and doubles none; a stratified sample with shares of 1 and 0 is a choice of strata."""
    e = load(spark, sf, "events").select("event_id", "event_type")
    one, two = e.randomSplit([0.3, 0.7], seed=5)
    both = one.withColumn("part", F.lit(1)).union(two.withColumn("part", F.lit(2))).groupBy("event_id").agg(F.count("*").alias("times"))
    kinds = e.sampleBy("event_type", {"click": 1.0, "error": 1.0}, seed=5).agg(F.count("*").alias("chosen"))
    return both.agg(F.sum("times").alias("n"), F.count_if(F.col("times") > 1).alias("in_both")).crossJoin(kinds)  # one row each


@R.query("SELECT o_orderpriority, round(corr(o_totalprice, o_custkey), 6) AS r, sum(o_orderkey % 7)::BIGINT AS rest, round(avg(pow(ln(o_totalprice), 2)), 6) AS squares, count(*) FILTER (o_custkey % 5 = 0) AS undivided FROM orders GROUP BY o_orderpriority")
def op_math(spark, sf):
    return load(spark, sf, "orders").groupBy("o_orderpriority").agg(
        F.round(F.corr("o_totalprice", "o_custkey"), 6).alias("r"), F.sum(F.pmod("o_orderkey", F.lit(7))).alias("rest"),
        F.round(F.avg(F.pow(F.ln("o_totalprice"), F.lit(2))), 6).alias("squares"), F.count_if(F.try_divide(F.lit(1), F.col("o_custkey") % 5).isNull()).alias("undivided"))


@R.query("WITH c AS (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL) SELECT user_id, count(*) AS kinds, count(*) FILTER (n > 12) AS frequent, (sum(2 * n) + sum(n))::BIGINT AS thrice FROM c GROUP BY user_id")
def op_maps(spark, sf):
    counts = load(spark, sf, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))  # five kinds
    twice = F.map_zip_with("m", F.transform_values("m", lambda k, v: v * 2), lambda k, a, b: a + b)
    return m.select("user_id", F.size("m").cast("long").alias("kinds"), F.size(F.map_filter("m", lambda k, v: v > 12)).cast("long").alias("frequent"), F.aggregate(F.map_values(twice), F.lit(0).cast("long"), lambda a, x: a + x).alias("thrice"))


@R.query("SELECT doc_id, CASE WHEN regexp_matches(text, '[!#$%&*]') THEN 'vulnerable' ELSE 'benign' END AS answer FROM documents")
def batch_responder(spark, sf):
    """A model called with 64 prompts at a time; a fixed rule stands for it here."""
    call = lambda prompts: ["vulnerable" if p and any(c in p for c in "!#$%&*") else "benign" for p in prompts]
    return respond.batch_answers(load(spark, sf, "documents").select("doc_id", F.col("text").alias("prompt")), call, "doc_id")


@R.query("SELECT user_id, count(*) AS answers, count(*) FILTER (event_type = 'error') AS refused FROM events GROUP BY user_id")
def table_responder(spark, sf):
    """Stored answers joined to their prompts, as if a model had been run before."""
    e = load(spark, sf, "events")
    answers = e.select("user_id", F.col("event_type").alias("answer"), F.lit("stored").alias("model"))
    out = respond.stored_answers(e.select("user_id").distinct(), answers, "user_id", "stored")
    return out.groupBy("user_id").agg(F.count("answer").alias("answers"), F.count_if(F.col("answer") == "error").alias("refused"))
