"""Sinks for training records and samples."""

from __future__ import annotations

from pyspark.sql import DataFrame


def write_samples(df: DataFrame, path: str) -> None:
    """Parquet by split and language, files clustered by class for min/max skipping."""
    df.repartition("split", "lang").sortWithinPartitions("cwe").write.mode("overwrite").partitionBy("split", "lang").parquet(path)


def write_shards(records: DataFrame, path: str) -> None:
    """JSON lines in the order of key, range-partitioned: shards in name order are the curriculum."""
    records.repartitionByRange("key").sortWithinPartitions("key").write.mode("overwrite").json(path)


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int = 16) -> None:
    """A table bucketed and sorted by key: later joins on it don't shuffle this side."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)
