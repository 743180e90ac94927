"""Structured Streaming forms for incremental collections and live answers."""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from detectlab.operators.overlap import distinct_grams


def file_stream(spark: SparkSession, folder: str, schema: T.StructType, files: int = 1) -> DataFrame:
    """New Parquet files of a folder, a few a batch."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(folder)


def event_time(df: DataFrame, column: str = "ts") -> DataFrame:
    """Times without a zone are refused as event time: cast first."""
    return df.withColumn(column, F.col(column).cast("timestamp"))


def tumbling(df: DataFrame, width: str = "1 hour", late: str = "10 minutes", slide: str | None = None) -> DataFrame:
    """Answers by window and kind; slide makes the windows overlap."""
    return df.withWatermark("ts", late).groupBy(F.window("ts", width, slide), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("value"))


def bursts(df: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    """Runs of answers of one user with no longer gap between them."""
    return df.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))


def first_seen(df: DataFrame, key: str, late: str = "10 minutes") -> DataFrame:
    return df.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def answered(prompts: DataFrame, answers: DataFrame, within: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    """Prompts with the answers that came within the time; both sides forget behind their watermark."""
    p = prompts.withWatermark("asked_at", late).alias("p")
    a = answers.withWatermark("answered_at", late).alias("a")
    return p.join(a, F.expr(f"p.prompt_id = a.answer_to AND a.answered_at >= p.asked_at AND a.answered_at <= p.asked_at + interval {within}"))


def contaminated(stream: DataFrame, test: DataFrame, id_column: str, text: str, test_text: str = "text", n: int = 20) -> DataFrame:
    """Ids of streamed rows that share a run of n tokens with a static test set, for which a broadcast is checked by the caller."""
    grams = distinct_grams(test.withColumn("_one", F.lit(0)), "_one", test_text, n).select("h").distinct()
    return distinct_grams(stream, id_column, text, n).join(grams, "h", "left_semi").select("id")


def early_votes(df: DataFrame, most: int = 16):
    """user_id, answer, used, decided: the answer as soon as no other can overtake it among the first ``most``, or at the end of those. State is dropped once decided."""
    import pandas as pd
    from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

    class Votes(StatefulProcessor):
        def init(self, handle: StatefulProcessorHandle) -> None:
            self.state = handle.getValueState("votes", "counts map<string,int>, used int, done boolean")

        def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:
            counts, used, done = self.state.get() if self.state.exists() else ({}, 0, False)
            counts, out = dict(counts or {}), []
            for pdf in rows:
                for answer in pdf.sort_values(["ts", "event_id"])["event_type"]:
                    if done:
                        break
                    counts[answer] = counts.get(answer, 0) + 1
                    used += 1
                    ranked = sorted(counts.values(), reverse=True)
                    lead = ranked[0] - (ranked[1] if len(ranked) > 1 else 0)
                    if used >= most or lead > most - used:
                        done = True
                        out.append((key[0], max(counts, key=lambda a: counts[a]), used, lead > most - used))
            self.state.update(({} if done else counts, used, done))
            yield pd.DataFrame(out, columns=["user_id", "answer", "used", "decided"])

        def close(self) -> None:
            pass

    return df.groupBy("user_id").transformWithStateInPandas(Votes(), "user_id long, answer string, used int, decided boolean", "append", "None")


def run_once(df: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Runs the stream over what is there and returns its result: a memory sink, for tests and small results."""
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name)


@contextmanager
def state_on_disk(spark: SparkSession):
    """State of the streams started within is kept by RocksDB on the executors' disks, not on their heaps."""
    name = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(name, None)
    spark.conf.set(name, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        yield
    finally:
        spark.conf.unset(name) if before is None else spark.conf.set(name, before)


def run_to_files(df: DataFrame, folder: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Runs the stream over what is there into Parquet files and reads them: none of its rows reach the driver.

    append: by Spark's file sink. complete: each batch writes the whole result under its own number; the last is read.
    """
    spark, last = df.sparkSession, []

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/{number}")
        last[:] = [number]

    with state_on_disk(spark):
        w = df.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True)
        q = (w.format("parquet").option("path", folder) if mode == "append" else w.foreachBatch(write)).start()
        q.awaitTermination()
    if mode == "append":
        return spark.read.schema(df.schema).parquet(folder)
    return spark.read.schema(df.schema).parquet(f"{folder}/{last[0]}") if last else spark.createDataFrame([], df.schema)


def upsert_sink(df: DataFrame, folder: str, checkpoint: str):
    """Writes each batch under its own number, so that a batch that runs again replaces itself."""

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/batch={number}")

    return df.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
