"""Streams over all that is there equal the batch; late rows are dropped."""

import datetime as dt
import glob
import os

from pyspark.sql import functions as F

from detectlab.sources.tables import load
from detectlab.streaming import streams

SF = "/root/testdata/sf0.001"


def test_early_votes_agree_with_the_full_vote(spark, tmp_path):
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    e = load(spark, SF, "events").select("event_id", "user_id", "ts", "event_type")
    e.coalesce(1).write.parquet(f"{tmp_path}/in")
    s = streams.event_time(streams.file_stream(spark, f"{tmp_path}/in", e.schema))
    got = {r.user_id: r for r in streams.run_once(streams.early_votes(s, 8), "early", f"{tmp_path}/c", "append").collect()}
    votes = {}
    for r in sorted(e.collect(), key=lambda r: (r.user_id, r.ts, r.event_id)):
        votes.setdefault(r.user_id, []).append(r.event_type)
    full = {u: v[:8] for u, v in votes.items() if len(v) >= 8}
    assert set(full) <= set(got)
    for u, v in full.items():
        counts = {a: v.count(a) for a in v}
        if got[u].decided:
            assert counts[got[u].answer] == max(counts.values()) and list(counts.values()).count(max(counts.values())) == 1


def test_late_rows_are_dropped(spark, tmp_path):
    t = dt.datetime(2024, 1, 1, 12)
    schema = "ts timestamp, event_type string, value double"
    parts = [[(t, "a", 1.0)], [(t + dt.timedelta(hours=3), "a", 1.0)], [(t + dt.timedelta(hours=3, minutes=1), "a", 1.0)], [(t + dt.timedelta(minutes=1), "a", 1.0)], [(t + dt.timedelta(hours=9), "a", 1.0)]]
    for k, rows in enumerate(parts):
        spark.createDataFrame(rows, schema).coalesce(1).write.parquet(f"{tmp_path}/in/p{k}")
        for f in glob.glob(f"{tmp_path}/in/p{k}/*"):
            os.utime(f, (1_700_000_000 + 60 * k,) * 2)  # files are taken in order of time
    src = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(f"{tmp_path}/in")
    out = streams.run_once(streams.tumbling(src), "late", f"{tmp_path}/c")
    assert sorted(r.n for r in out.collect()) == [1, 2]  # a row is late by the watermark of the batch before


def test_stream_decontamination(spark, tmp_path):
    docs, bench = load(spark, SF, "documents").select("doc_id", "text"), load(spark, SF, "benchmark")
    docs.write.parquet(f"{tmp_path}/in")
    s = streams.file_stream(spark, f"{tmp_path}/in", docs.schema)
    live = streams.run_once(streams.contaminated(s, bench, "doc_id", "text"), "dirty", f"{tmp_path}/c")
    batch = streams.contaminated(docs, bench, "doc_id", "text")
    assert {r.id for r in live.collect()} == {r.id for r in batch.collect()}


def test_foreach_batch_is_idempotent(spark, tmp_path):
    spark.range(5).write.parquet(f"{tmp_path}/in")
    s = spark.readStream.schema("id long").parquet(f"{tmp_path}/in")
    streams.upsert_sink(s, f"{tmp_path}/out", f"{tmp_path}/c").awaitTermination()
    assert spark.read.parquet(f"{tmp_path}/out").agg(F.sum("id")).first()[0] == 10


def test_plans(spark):
    """Filters and columns reach the scan; nothing multiplies rows."""
    from detectlab import plans

    queries, _ = plans.collect()
    plan = queries["op_scan_pushdown"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters" in plan and "l_orderkey" not in plan
    for name in ("reject_shortest", "dedup_first", "majority_vote", "decontaminate"):
        assert "CartesianProduct" not in queries[name](spark, SF)._jdf.queryExecution().executedPlan().toString()
