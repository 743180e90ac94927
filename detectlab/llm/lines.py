"""Line deduplication over windows of three lines, in DataFrame operations only.

Every run of three consecutive lines is hashed (96 bits). A run that occurs more
than once keeps its first place, by doc_id, then the row's text hash, then line;
the lines of later places are removed, overlapping runs merged.

Texts are read once for the runs, which are written as hashes and places (32 bytes a
run), and once more for the result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from detectlab.llm.frames import cut

_LAST = 9223372036854775807


def _rows(docs: DataFrame) -> DataFrame:
    return docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(_LAST)).alias("at_id"), F.xxhash64("doc_id", "text").alias("at_row"), F.struct("*").alias("doc"))


def repeated_lines(docs: DataFrame, span: int = 3, broadcast_rows: int = 200_000) -> DataFrame:
    """at_id, at_row, covered: the line numbers (from 0) that each row loses.

    broadcast_rows: repeated runs (40 bytes each) up to which they are broadcast to the places; more are joined by a shuffle.
    """
    lines = F.split(F.col("doc.text"), "\n", -1)
    rows = _rows(docs.select("doc_id", "text")).select("at_id", "at_row", lines.alias("lines")).where(F.size("lines") >= span)

    def window(i: Column) -> Column:
        own = [F.col("lines")[i + k] for k in range(span)]
        return F.struct(i.cast("int").alias("line"), F.xxhash64(*own).alias("h"), F.hash(*own).alias("g"), F.exists(F.array(*own), lambda x: x.rlike(r"[^\x20\x09-\x0D]")).alias("words"))

    found = cut(rows.select("at_id", "at_row", F.inline(F.transform(F.sequence(F.lit(0), F.size("lines") - span), window))).where("words").drop("words"))
    place = F.struct("at_id", "at_row", "line")
    twice = cut(found.groupBy("h", "g").agg(F.min(place).alias("first"), F.count("*").alias("n")).where("n > 1").drop("n"))
    twice = F.broadcast(twice) if twice.count() <= broadcast_rows else twice
    later = found.join(twice, ["h", "g"]).where(place > F.col("first"))
    each = F.transform(F.sequence(F.lit(0), F.lit(span - 1)), lambda k: k + F.col("line"))
    return later.groupBy("at_id", "at_row").agg(F.array_distinct(F.flatten(F.collect_list(each))).alias("covered"))


def dedup_lines(docs: DataFrame, span: int = 3) -> DataFrame:
    """doc (struct of docs' columns, its text without the lines removed), n_lines, n_removed. One row per input row.

    Null text stays null with no lines; texts of fewer than three lines and runs
    without a word stay. Rows without doc_id come last. Repeated rows (same doc_id
    and text) are one document: each loses the same lines.
    """
    lines = F.split(F.col("doc.text"), "\n", -1)
    gone = F.coalesce(F.size("covered"), F.lit(0))
    joined = _rows(docs).join(repeated_lines(docs, span), ["at_id", "at_row"], "left")
    stay = F.array_except(F.sequence(F.lit(0), F.size("lines") - 1), F.col("covered"))
    text = F.when(gone > 0, F.array_join(F.transform(stay, lambda i: F.col("lines")[i]), "\n")).otherwise(F.col("doc.text"))
    return joined.withColumn("lines", lines).select(
        F.col("doc").withField("text", text).alias("doc"),
        F.coalesce(F.size("lines"), F.lit(0)).cast("long").alias("n_lines"),
        F.coalesce(gone, F.lit(0)).cast("long").alias("n_removed"),
    )
