"""Operators that users of the methods need around them, each on a given table."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from detectlab.plans.registry import Registry
from detectlab.sources.tables import load

R = Registry()
r2 = lambda c: F.round(c, 2)


@R.query("SELECT l_returnflag, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem WHERE l_discount BETWEEN 0.02 AND 0.06 AND l_quantity > 10 GROUP BY l_returnflag")
def op_scan_pushdown(spark, sf):
    """Two filters and three columns: both reach the Parquet scan."""
    return load(spark, sf, "lineitem").where("l_discount BETWEEN 0.02 AND 0.06 AND l_quantity > 10").groupBy("l_returnflag").agg(F.count("*").alias("n"), r2(F.sum("l_quantity")).alias("quantity"))


def _folder(spark) -> str:
    sc = spark.sparkContext
    base = sc.getCheckpointDir() or sc.getConf().get("spark.checkpoint.dir") or tempfile.gettempdir()  # the last only in tests
    return f"{base}/detectlab-ops-{uuid.uuid4().hex}"


def _round_trip(kind):
    @R.query("SELECT conv_id, turn, role, length(text) AS chars FROM conversations", name=f"op_round_trip_{kind}")
    def run(spark, sf):
        schema = T.StructType([T.StructField("conv_id", T.LongType()), T.StructField("turn", T.LongType()), T.StructField("role", T.StringType()), T.StructField("text", T.StringType())])
        path = f"{_folder(spark)}/{kind}"
        df = load(spark, sf, "conversations").select("conv_id", "turn", "role", "text")
        extra = {"multiLine": True, "header": True, "quote": '"', "escape": '"'} if kind == "csv" else {}
        write = {k: v for k, v in extra.items() if k != "multiLine"}
        getattr(df.write.mode("overwrite").options(**write), kind)(path)
        back = getattr(spark.read.schema(schema).options(**extra), kind)(path)
        return back.select("conv_id", "turn", "role", F.length("text").cast("long").alias("chars"))


for _kind in ("json", "csv", "orc", "parquet"):
    _round_trip(_kind)


@R.query("SELECT doc_id AS sample_id, length(text) AS chars FROM documents")
def op_data_source(spark, sf):
    """The documents as a feed of pages, read by a data source of our own, a page a task."""
    from detectlab.sources.snippets import SnippetFeed, write_pages

    path = f"{_folder(spark)}/feed"
    write_pages(load(spark, sf, "documents").select(F.col("doc_id").cast("long").alias("sample_id"), F.col("text").alias("code")), path)
    spark.dataSource.register(SnippetFeed)
    return spark.read.format("snippets").option("path", path).load().select("sample_id", F.length("code").cast("long").alias("chars"))


@R.query("SELECT doc_id, lang IN ('en', 'de') AS listed, regexp_matches(text, '[0-9]') AS digits, lang IS NOT DISTINCT FROM 'en' AS english, len(list_filter(string_split(text, ' '), lambda x: length(x) > 20)) > 0 AS long_word FROM documents")
def op_filters(spark, sf):
    return load(spark, sf, "documents").select("doc_id", F.col("lang").isin("en", "de").alias("listed"), F.col("text").rlike("[0-9]").alias("digits"), F.col("lang").eqNullSafe("en").alias("english"), F.exists(F.split("text", " "), lambda x: F.length(x) > 20).alias("long_word"))


def _join(hint):
    @R.query("SELECT o_orderpriority, count(*) AS lines, round(sum(l_extendedprice), 2) AS price FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderpriority", name=f"op_join_{hint}")
    def run(spark, sf):
        o, li = load(spark, sf, "orders"), load(spark, sf, "lineitem")
        return o.hint(hint).join(li, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("lines"), r2(F.sum("l_extendedprice")).alias("price"))


for _hint in ("merge", "shuffle_hash"):
    _join(_hint)


@R.query("SELECT 'semi' AS kind, count(*) AS n FROM documents SEMI JOIN labels USING (doc_id) UNION ALL SELECT 'anti', count(*) FROM documents ANTI JOIN labels USING (doc_id) UNION ALL SELECT 'full', count(*) FROM documents FULL JOIN labels USING (doc_id)")
def op_join_kinds(spark, sf):
    d, la = load(spark, sf, "documents").select("doc_id"), load(spark, sf, "labels").select("doc_id")
    out = None
    for name, how in (("semi", "left_semi"), ("anti", "left_anti"), ("full", "full_outer")):
        one = d.join(la, "doc_id", how).agg(F.count("*").alias("n")).select(F.lit(name).alias("kind"), "n")
        out = one if out is None else out.union(one)
    return out


@R.query("SELECT a.event_id, count(*) AS near FROM events a JOIN events b ON b.user_id = a.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR GROUP BY a.event_id")
def op_range_join(spark, sf):
    """Events of the same user within the next hour: an equi-join on hour buckets, each row in its own and the next."""
    e = load(spark, sf, "events").select("event_id", "user_id", F.col("ts").cast("timestamp").cast("double").alias("t"))
    hour = F.floor(F.col("t") / 3600)
    a = e.select("event_id", "user_id", "t", F.explode(F.array(hour, hour + 1)).alias("h"))
    b = e.select(F.col("user_id"), F.col("t").alias("bt"), hour.alias("h"))
    return a.join(b, ["user_id", "h"]).where((F.col("bt") > F.col("t")) & (F.col("bt") <= F.col("t") + 3600)).groupBy("event_id").agg(F.count("*").alias("near"))


@R.query("SELECT e.event_id, (SELECT max(v.event_id) FROM events v WHERE v.user_id = e.user_id AND v.event_id % 10 = 0 AND (v.ts, v.event_id) <= (e.ts, e.event_id) AND (v.ts, v.event_id) = (SELECT max((w.ts, w.event_id)) FROM events w WHERE w.user_id = e.user_id AND w.event_id % 10 = 0 AND (w.ts, w.event_id) <= (e.ts, e.event_id))) AS last_version FROM events e")
def op_asof_join(spark, sf):
    """For each event the last version (every tenth event) of its user at the time: one sort, no join."""
    e = load(spark, sf, "events")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return e.select("event_id", F.last(F.when(F.col("event_id") % 10 == 0, F.col("event_id")), ignorenulls=True).over(w).alias("last_version"))


@R.query("SELECT event_type, count(*) AS n, count(*) FILTER (value > 50) AS large, bool_or(value > 99) AS any_top, arg_min(event_id, (value, event_id)) AS least, arg_max(event_id, (value, event_id)) AS most, round(quantile_cont(value, 0.5), 6) AS median, count(DISTINCT user_id) AS users FROM events GROUP BY event_type")
def op_aggregates(spark, sf):
    key = F.struct("value", "event_id")
    return load(spark, sf, "events").groupBy("event_type").agg(F.count("*").alias("n"), F.count_if(F.col("value") > 50).alias("large"), F.bool_or(F.col("value") > 99).alias("any_top"), F.min_by("event_id", key).alias("least"), F.max_by("event_id", key).alias("most"), F.round(F.percentile("value", 0.5), 6).alias("median"), F.countDistinct("user_id").alias("users"))


@R.query("SELECT lang, source, count(*) AS n, count(quality) AS labelled, grouping_id(lang, source)::BIGINT AS gid FROM documents LEFT JOIN labels USING (doc_id) GROUP BY ROLLUP (lang, source)")
def op_rollup(spark, sf):
    j = load(spark, sf, "documents").join(load(spark, sf, "labels"), "doc_id", "left")
    return j.rollup("lang", "source").agg(F.count("*").alias("n"), F.count("quality").alias("labelled"), F.grouping_id().alias("gid"))


@R.query("SELECT l_linestatus, coalesce(sum(l_quantity) FILTER (l_returnflag = 'A'), 0)::DOUBLE AS A, coalesce(sum(l_quantity) FILTER (l_returnflag = 'N'), 0)::DOUBLE AS N, coalesce(sum(l_quantity) FILTER (l_returnflag = 'R'), 0)::DOUBLE AS R FROM lineitem GROUP BY l_linestatus")
def op_pivot(spark, sf):
    return load(spark, sf, "lineitem").groupBy("l_linestatus").pivot("l_returnflag", ["A", "N", "R"]).agg(F.sum("l_quantity").cast("double")).na.fill(0.0)


@R.query("SELECT doc_id, kind, v FROM labels, LATERAL (VALUES ('quality', quality), ('toxic', toxic)) t(kind, v)")
def op_unpivot(spark, sf):
    return load(spark, sf, "labels").unpivot("doc_id", ["quality", "toxic"], "kind", "v")


@R.query("SELECT o_orderkey, row_number() OVER w::INT AS rn, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority)::INT AS dr, ntile(4) OVER w::INT AS nt, lag(o_orderkey) OVER w AS before, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 2) AS last3 FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey)")
def op_windows(spark, sf):
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey")
    return load(spark, sf, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.dense_rank().over(Window.partitionBy("o_custkey").orderBy("o_orderpriority")).alias("dr"), F.ntile(4).over(w).alias("nt"), F.lag("o_orderkey").over(w).alias("before"), r2(F.sum("o_totalprice").over(w.rowsBetween(-2, 0))).alias("last3"))


@R.query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def op_top_k(spark, sf):
    return load(spark, sf, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20)


@R.query("SELECT 'intersect' AS kind, count(*) AS n FROM (SELECT c_nationkey FROM customer INTERSECT SELECT s_nationkey FROM supplier) UNION ALL SELECT 'except', count(*) FROM (SELECT c_nationkey FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier) UNION ALL SELECT 'union', count(*) FROM (SELECT c_nationkey FROM customer UNION SELECT s_nationkey FROM supplier)")
def op_sets(spark, sf):
    c, s = load(spark, sf, "customer").select(F.col("c_nationkey").alias("k")), load(spark, sf, "supplier").select(F.col("s_nationkey").alias("k"))
    out = None
    for name, df in (("intersect", c.intersect(s)), ("except", c.exceptAll(s)), ("union", c.union(s).distinct())):
        one = df.agg(F.count("*").alias("n")).select(F.lit(name).alias("kind"), "n")
        out = one if out is None else out.union(one)
    return out


@R.query("SELECT doc_id FROM documents WHERE (doc_id * 48271 + 7 * 16807 + 12345) % 2147483647 * 69621 % 2147483647 % 100 < 10")
def op_sample(spark, sf):
    """A tenth of the rows by seeded hash: the feature is a sample."""
    from detectlab.operators.corpus import seeded

    return load(spark, sf, "documents").where(seeded("doc_id", 7) % 100 < 10).select("doc_id")


@R.query("SELECT doc_id, upper(lang) AS u, replace(source, 'src', 's') AS r, levenshtein(lang, 'en') AS d, sha256(text) AS h, concat_ws('-', lang, source) AS c FROM documents")
def op_strings(spark, sf):
    return load(spark, sf, "documents").select("doc_id", F.upper("lang").alias("u"), F.replace("source", F.lit("src"), F.lit("s")).alias("r"), F.levenshtein("lang", F.lit("en")).cast("long").alias("d"), F.sha2("text", 256).alias("h"), F.concat_ws("-", "lang", "source").alias("c"))


@R.query("SELECT date_trunc('month', ts)::DATE AS month, event_type, count(*) AS n, max(date_diff('day', TIMESTAMP '2024-01-01', ts))::INT AS last_day FROM events GROUP BY ALL")
def op_dates(spark, sf):
    e = load(spark, sf, "events")
    return e.groupBy(F.to_date(F.date_trunc("month", "ts")).alias("month"), "event_type").agg(F.count("*").alias("n"), F.max(F.datediff("ts", F.lit("2024-01-01"))).alias("last_day"))


@R.query("SELECT vec_id, round(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[]), 4) AS norm2, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings")
def op_arrays(spark, sf):
    d = F.transform("embedding", lambda x: x.cast("double"))
    return load(spark, sf, "embeddings").select("vec_id", F.round(F.aggregate(F.zip_with(d, d, lambda a, b: a * b), F.lit(0.0), lambda a, x: a + x), 4).alias("norm2"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"))


@R.query("SELECT event_id, (props->>'$.k')::INT AS k FROM events")
def op_json(spark, sf):
    return load(spark, sf, "events").select("event_id", F.from_json("props", "k int").k.alias("k"))


@R.query("SELECT event_id, (props->>'$.k')::INT AS k FROM events")
def op_variant(spark, sf):
    return load(spark, sf, "events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "int").alias("k"))


@R.query("SELECT d.doc_id, coalesce(quality, -1) AS quality, nullif(toxic, 0) AS toxic FROM documents d LEFT JOIN labels USING (doc_id)")
def op_nulls(spark, sf):
    j = load(spark, sf, "documents").join(load(spark, sf, "labels"), "doc_id", "left")
    return j.select("doc_id", F.coalesce("quality", F.lit(-1)).alias("quality"), F.nullif("toxic", F.lit(0)).alias("toxic"))


@R.query("SELECT user_id, count(*) AS n, round(max(value) - min(value), 6) AS spread FROM events GROUP BY user_id")
def op_grouped_arrow(spark, sf):
    import pyarrow as pa
    import pyarrow.compute as pc

    def spread(t: pa.Table) -> pa.Table:
        v = t.column("value")
        return pa.table({"user_id": t.column("user_id").slice(0, 1), "n": pa.array([len(v)], pa.int64()), "spread": pa.array([round(pc.max(v).as_py() - pc.min(v).as_py(), 6)])})

    return load(spark, sf, "events").select("user_id", "value").groupBy("user_id").applyInArrow(spread, "user_id long, n long, spread double")


@R.query("SELECT lang, count(*) AS grams FROM (SELECT lang, unnest(range(0, len(string_split(text, ' ')) - 1)) AS p FROM documents) GROUP BY lang")
def op_udtf(spark, sf):
    @F.udtf(returnType="a string, b string")
    class Pairs:
        def eval(self, text: str):
            w = (text or "").split(" ")
            yield from zip(w, w[1:], strict=False)

    spark.udtf.register("word_pairs", Pairs)
    load(spark, sf, "documents").createOrReplaceTempView("op_udtf_documents")
    return spark.sql("SELECT lang, count(*) AS grams FROM op_udtf_documents, LATERAL word_pairs(text) GROUP BY lang")


@R.query("WITH RECURSIVE r(n, k) AS (SELECT n_nationkey, 0 FROM nation WHERE n_nationkey = 0 UNION ALL SELECT (n + 7) % 25, k + 1 FROM r WHERE k < 12) SELECT n, k FROM r")
def op_recursion(spark, sf):
    load(spark, sf, "nation").createOrReplaceTempView("op_nation")
    return spark.sql("WITH RECURSIVE r(n, k) AS (SELECT n_nationkey, 0 FROM op_nation WHERE n_nationkey = 0 UNION ALL SELECT (n + 7) % 25, k + 1 FROM r WHERE k < 12) SELECT n, k FROM r")


@R.query()
def op_minhash_lsh(spark, sf):
    """Pairs of classes whose sets of tokens share more than 90 % of their union, and the copies of each class."""
    from detectlab.functions.tokens import tokens
    from detectlab.operators import minhash

    return minhash.near_sets(load(spark, sf, "documents"), "doc_id", tokens("text"), 90)


@R.query("SELECT event_type, date_trunc('hour', ts) AS hour, count(*) AS n FROM events GROUP BY ALL")
def op_stream_tumbling(spark, sf):
    """The stream over all that is there equals the batch answer."""
    from detectlab.streaming import streams

    path = f"{_folder(spark)}/events-stream"
    load(spark, sf, "events").write.mode("overwrite").parquet(path)
    s = streams.event_time(streams.file_stream(spark, path, load(spark, sf, "events").schema))
    out = streams.run_once(streams.tumbling(s), "op_stream_tumbling", f"{path}-checkpoint", "complete")
    return out.select("event_type", F.col("window.start").cast("timestamp_ntz").alias("hour"), "n")


