"""Mixing sources to target weights in equal blocks of words.

The words of each source are laid out shard by shard in a seeded order and cut
into blocks. Sainte-Lague apportionment gives every source, then every shard of
it, a whole number of blocks; a shard takes all its blocks as often as its quota
allows and the rest in seeded order.
"""

from __future__ import annotations

import heapq
from fractions import Fraction

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from detectlab.llm.frames import cut

WORD = r"[^\x20\x09-\x0D]+"


def targets(sizes: list[int], weights: list[float], most: float = 3.0, total: float | None = None) -> list[float]:
    """total shared by weight; what is above most times a source's size goes to the others by weight."""
    left, out = float(sum(sizes) if total is None else total), [0.0] * len(sizes)
    active = set(range(len(sizes)))
    while active:
        weight = sum(weights[i] for i in active)
        share = {i: left * weights[i] / weight for i in active}
        above = [i for i in sorted(active) if share[i] > most * sizes[i]]
        if not above:
            for i in active:
                out[i] = share[i]
            break
        for i in above:
            out[i] = most * sizes[i]
            left -= out[i]
            active.discard(i)
    return out


def sainte_lague(weights: list[float], seats: int) -> list[int]:
    """Seats by highest quotients weight/(2k+1); ties go to the earlier.

    All seats whose quotient is above a common divisor are given at once; only the
    last few are dealt one by one.
    """
    total, w = sum(weights), np.asarray(weights, float)
    if seats <= 0 or total <= 0:
        return [0] * len(weights)
    low, high = 0.0, 4.0 * total
    for _ in range(200):  # smallest divisor found that gives no more than all seats
        mid = (low + high) / 2
        if np.floor(w / mid + 0.5).sum() <= seats:
            high = mid
        else:
            low = mid
        if high - low <= 1e-13 * high:
            break
    out = np.floor(w / (high * (1 + 1e-9)) + 0.5).astype(np.int64).tolist()
    queue = [(-Fraction(v) / (2 * out[i] + 1), i) for i, v in enumerate(weights) if v > 0]
    heapq.heapify(queue)
    for _ in range(seats - sum(out)):
        _, i = heapq.heappop(queue)
        out[i] += 1
        heapq.heappush(queue, (-Fraction(weights[i]) / (2 * out[i] + 1), i))
    return out


def takes(docs: DataFrame, *, weights: tuple[float, ...] = (1, 2, 3), share: float = 1.0, most: int = 3, block_words: int = 64, shard_words: int = 1 << 18, most_shards: int = 1 << 18, seed: int = 17) -> DataFrame:
    """doc_id, row (hash of the row), size, source_size, target, taken. One row per input row.

    Sources by code point, null last, get the weights in turn. taken is the words
    the mix takes, repeats counted, at most ``most`` times the document's size.
    Null or empty text has size 0 and is never taken. Repeated rows count each. An
    empty table gives no rows. A source has most_shards shards at most, larger ones
    beyond that, so that one task can hold their counts. The names of sources, one row each, go to the
    driver; documents never do.
    """
    spark = docs.sparkSession
    size = F.coalesce(F.regexp_count(F.col("text"), F.lit(WORD)), F.lit(0)).cast("long")
    order = F.xxhash64(F.lit(seed), F.col("doc_id"), F.xxhash64("text"))
    sized = cut(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("doc_id", "text", "source").alias("row"), "source", size.alias("size"), order.alias("order")))
    found = sorted(((r.source, r.size) for r in sized.groupBy("source").agg(F.sum("size").alias("size")).collect()), key=lambda x: (x[0] is None, x[0] or ""))
    goal = targets([n for _, n in found], [weights[k % len(weights)] for k in range(len(found))], most, share * sum(n for _, n in found))
    quota = sainte_lague(goal, round(sum(goal) / block_words))
    shards = [min(most_shards, max(1, -(-n // shard_words))) for _, n in found]
    names = spark.createDataFrame(
        [(k, s, n, float(g), q, m) for k, ((s, n), g, q, m) in enumerate(zip(found, goal, quota, shards, strict=True))],
        "sid int, source string, source_size long, target double, quota long, shards long",
    )
    names = F.broadcast(names) if len(found) <= 100_000 else names
    match = F.col("d.source").eqNullSafe(F.col("s.source"))
    # rows that are alike are one entry with a count, so that they share what is taken evenly
    laid = (
        sized.alias("d").join(names.alias("s"), match).where("size > 0")
        .select("sid", F.pmod("order", F.col("shards")).alias("shard"), "order", "doc_id", "row", "size", "quota", "shards")
    )
    spread = laid.groupBy("sid", "shard").agg(F.sum("size").alias("words"), F.max("quota").alias("quota"))

    def seats(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("shard")
        blocks = [-(-int(w) // block_words) for w in pdf.words]
        given = sainte_lague([float(w) for w in pdf.words], int(pdf.quota.iloc[0]))
        given = [min(g, most * b) for g, b in zip(given, blocks, strict=True)]
        return pd.DataFrame({"sid": pdf.sid, "shard": pdf.shard, "blocks": blocks, "full": [g // b for g, b in zip(given, blocks, strict=True)], "extra": [g % b for g, b in zip(given, blocks, strict=True)]})

    shares = cut(spread.groupBy("sid").applyInPandas(seats, "sid int, shard long, blocks long, full long, extra long"))
    picked = (
        shares.where("extra > 0").select("sid", "shard", "extra", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("block"))
        .withColumn("n", F.row_number().over(Window.partitionBy("sid", "shard").orderBy(F.xxhash64(F.lit(seed), "sid", "shard", "block"), "block")))
        .where("n <= extra").select("sid", "shard", "block", F.lit(1).alias("hit"))
    )
    before = Window.partitionBy("sid", "shard").orderBy("order", "doc_id", "row").rowsBetween(Window.unboundedPreceding, -1)
    spans = laid.withColumn("start", F.coalesce(F.sum("size").over(before), F.lit(0))).withColumn("end", F.col("start") + F.col("size"))
    parts = spans.select("sid", "shard", "doc_id", "row", "start", "end", F.explode(F.expr(f"sequence(start div {block_words}, (end - 1) div {block_words})")).alias("block"))
    # shares is a small file, but its blocks grow with the input: no broadcast of what it is spread to
    overlap = F.least("end", (F.col("block") + 1) * block_words) - F.greatest("start", F.col("block") * block_words)
    extra = parts.join(picked.hint("merge"), ["sid", "shard", "block"]).groupBy("doc_id", "row", "start", "sid", "shard").agg(F.sum(overlap).alias("extra_words"))
    mine = spans.select("doc_id", "row", "sid", "shard", "start", "size")
    taken = (
        mine.join(shares.select("sid", "shard", "full"), ["sid", "shard"])
        .join(extra.withColumnRenamed("doc_id", "e_id").withColumnRenamed("row", "e_row"), (F.col("doc_id").eqNullSafe(F.col("e_id"))) & (F.col("row") == F.col("e_row")) & (mine["sid"] == extra["sid"]) & (mine["shard"] == extra["shard"]) & (mine["start"] == extra["start"]), "left")
        .groupBy("doc_id", "row").agg(F.sum(F.col("size") * F.col("full") + F.coalesce("extra_words", F.lit(0))).alias("all_taken"), F.count("*").alias("alike"))
    )
    out = sized.withColumnsRenamed({"doc_id": "r_id", "row": "r_row"}).join(taken, F.col("r_id").eqNullSafe(F.col("doc_id")) & (F.col("r_row") == F.col("row")), "left")
    out = out.alias("d").join(names.select("source", "source_size", "target").alias("s"), match, "left")
    even = F.expr("all_taken div alike")
    return out.select(F.col("r_id").alias("doc_id"), F.col("r_row").alias("row"), "size", "source_size", "target", F.coalesce(even, F.lit(0)).cast("long").alias("taken"))


def mix_rows(docs: DataFrame, **how) -> DataFrame:
    """The rows of docs that the mix takes words of, with size, target and taken after their own columns."""
    found = takes(docs, **how).where("taken > 0").dropDuplicates(["doc_id", "row"])
    found = found.select(F.col("doc_id").alias("t_id"), F.col("row").alias("t_row"), F.struct("size", "target", "taken").alias("mix"))
    rows = docs.select(F.struct("*").alias("doc"), F.col("doc_id").cast("long").alias("r_id"), F.xxhash64("doc_id", "text", "source").alias("r_row"))
    joined = rows.join(found, F.col("r_id").eqNullSafe(F.col("t_id")) & (F.col("r_row") == F.col("t_row")))
    clash = set(docs.columns)
    return joined.select("doc.*", *[F.col(f"mix.{c}").alias(c if c not in clash else f"mix_{c}") for c in ("size", "target", "taken")])
