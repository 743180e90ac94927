"""From raw documents to a training mix, in five stages.

Each stage takes (spark, docs, sf_dir) and works on all that the one before kept;
between stages the rows are written as Parquet and read again, so a lost executor
costs one stage at most. The first four return the columns of documents, the last
adds size, target and taken (words of the document in the mix, repeats counted).
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from detectlab.llm import decontam, jaccard, lines, mixing, quality
from detectlab.llm.frames import shared_dir, small_batches


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents within the base rules and their group's limits."""
    small_batches(spark)
    return quality.filter_quality(docs)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without later occurrences of three-line windows; n_chars follows the text."""
    out = lines.dedup_lines(docs)
    size = F.when(F.col("n_removed") > 0, F.length("doc.text")).otherwise(F.col("doc.n_chars")).cast(dict(docs.dtypes).get("n_chars", "long"))
    return out.select(*[size.alias(c) if c == "n_chars" else F.col(f"doc.`{c}`") for c in docs.columns])


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group that links of 80 % of five-word shingles make."""
    small_batches(spark)
    return jaccard.keep_one(docs, jaccard.Join(words=5, percent=80))


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no benchmark item is found."""
    small_batches(spark)
    return decontam.without_matches(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the mix of sources takes words of."""
    return mixing.mix_rows(docs)


STAGES = [("quality rules", quality_rules), ("line dedup", line_dedup), ("n-gram jaccard join", near_duplicates), ("benchmark decontamination", decontaminate), ("source mixing", mix_sources)]

#: Edit distance and apportionment have no SQL form; tests hold each stage against a brute-force one.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{k}")
        docs = spark.read.parquet(f"{folder}/{k}")
    return docs
