"""Helpers on sessions, partitions and cut lineage."""

from __future__ import annotations

import tempfile
import uuid
from weakref import WeakKeyDictionary

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The checkpoint folder all machines share. Where none is set, a local one on a local master (tests), else an error."""
    sc = spark.sparkContext
    set_already = sc.getCheckpointDir()
    if set_already:
        return set_already
    named = sc.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not named and not (sc.master == "local" or sc.master.startswith("local[")):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="detectlab-ckpt-"))
    return sc.getCheckpointDir()


_WRITTEN: WeakKeyDictionary[DataFrame, str] = WeakKeyDictionary()


def cut(df: DataFrame, batch_rows: int | None = None) -> DataFrame:
    """df as a table written to the shared folder, its lineage gone; release() removes it.

    batch_rows: rows of an Arrow batch while it is computed, for stages that hand whole texts to Python;
    the session's own setting is put back.
    """
    spark, name = df.sparkSession, "spark.sql.execution.arrow.maxRecordsPerBatch"
    path = f"{shared_dir(spark)}/cut-{uuid.uuid4().hex}"
    before = spark.conf.get(name)
    if batch_rows is not None:
        spark.conf.set(name, str(batch_rows))
    try:
        df.write.parquet(path)
    finally:
        if batch_rows is not None:
            spark.conf.set(name, before)
    out = spark.read.schema(df.schema).parquet(path)
    _WRITTEN[out] = path
    return out


def release(*tables: DataFrame) -> None:
    """Removes tables that cut() wrote, once nothing reads them any more."""
    for table in tables:
        path = _WRITTEN.pop(table, None)
        if path:
            sc = table.sparkSession.sparkContext
            where = sc._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(sc._jsc.hadoopConfiguration()).delete(where, True)


def small_batches(spark: SparkSession, rows: int = 1024) -> None:
    """Whole texts reach Python so many at once from now on, in what is computed later too. Only ever lowers the session's setting."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    now = int(spark.conf.get(name))
    spark.conf.set(name, str(rows if now <= 0 else min(rows, now)))  # 0 and less: no limit


def n_blocks(df: DataFrame) -> int:
    """Blocks for data dealt by key: follows the scan's splits, so it grows with the input."""
    spark = df.sparkSession
    shuffle = int(spark.conf.get("spark.sql.shuffle.partitions"))
    return max(shuffle, df.rdd.getNumPartitions())


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")
