"""Removing samples that share a run of 20 tokens, between sets and within one."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from detectlab.functions.tokens import gram_hashes, held, tokens, winnow
from detectlab.sources.tables import cut

N = 20
#: Grams of the smaller side up to which they are broadcast (8 bytes each).
PROBE_ROWS = 5_000_000


def grams(df: DataFrame, id_column: str, text: str, n: int = N) -> DataFrame:
    """id, pos, h: one row per n-gram. Only hashes are exploded, never the grams."""
    return held(df.select(F.col(id_column).alias("id"), F.col(text).alias("text")), t=tokens("text")).select("id", F.posexplode(gram_hashes(F.col("t"), n)).alias("pos", "h"))


def distinct_grams(df: DataFrame, id_column: str, text: str, n: int = N) -> DataFrame:
    """id, h: each once a row, before any shuffle."""
    t = held(df.select(F.col(id_column).alias("id"), F.col(text).alias("text")), t=tokens("text"))
    return t.select("id", F.explode(F.array_distinct(gram_hashes(F.col("t"), n))).alias("h"))


def _small(df: DataFrame) -> DataFrame:
    """Broadcast behind a count; beyond it a plain shuffle join."""
    return F.broadcast(df) if df.count() <= PROBE_ROWS else df


def fingerprints(df: DataFrame, id_column: str, text: str, n: int = N) -> DataFrame:
    """id, f: the least hash of n // 2 tokens in each run of n, so that rows that share a run share one of these."""
    k = n // 2
    t = held(df.select(F.col(id_column).alias("id"), F.col(text).alias("text")), t=tokens("text")).where(F.size("t") >= n)
    return held(t, g=gram_hashes(F.col("t"), k)).select("id", F.explode(winnow(F.col("g"), n - k + 1)).alias("f"))


def _of(df: DataFrame, id_column: str, ids: DataFrame) -> DataFrame:
    """Rows of df whose id is among ids (id)."""
    return df.join(ids.withColumnRenamed("id", id_column), id_column, "left_semi")


def shared_grams(a: DataFrame, b: DataFrame, *, a_id: str, b_id: str, a_text: str = "text", b_text: str = "text", n: int = N, strategy: str = "winnow") -> tuple[DataFrame, DataFrame]:
    """(id, h) of a and of b; of a, with strategy 'winnow', only of rows that share a fingerprint with b. Other rows
    have no gram in common, and no text goes to a pair of rows."""
    if strategy == "winnow":
        marks = cut(fingerprints(b, b_id, b_text, n).select("f").distinct())
        a = _of(a, a_id, cut(fingerprints(a, a_id, a_text, n).join(_small(marks), "f", "left_semi").select("id").distinct()))
    return distinct_grams(a, a_id, a_text, n), cut(distinct_grams(b, b_id, b_text, n))


def overlap_pairs(a: DataFrame, b: DataFrame, *, a_id: str, b_id: str, a_text: str = "text", b_text: str = "text", n: int = N, strategy: str = "grams") -> DataFrame:
    """a_id, b_id of rows that share a run of n tokens. strategy 'winnow' makes grams only of rows that share a fingerprint."""
    left, right = shared_grams(a, b, a_id=a_id, b_id=b_id, a_text=a_text, b_text=b_text, n=n, strategy=strategy)
    return left.join(_small(right.withColumnRenamed("id", "_other")), "h").select(F.col("id").alias(a_id), F.col("_other").alias(b_id)).distinct()


def decontaminate(train: DataFrame, test: DataFrame, *, train_id: str, test_id: str, drop: str = "train", n: int = N) -> DataFrame:
    """The kept rows: of train without overlaps with test (drop 'train'), of test (drop 'test'), or ids of both with their side (drop 'both').
    Sides meet in semi-joins on grams: no pairs are made, however common a run is."""
    left, right = shared_grams(train, test, a_id=train_id, b_id=test_id, n=n)
    hit = lambda one, other: cut(one.join(_small(cut(other.select("h").distinct())), "h", "left_semi").select("id").distinct())
    clean = lambda df, c, gone: df.join(gone.withColumnRenamed("id", c), c, "left_anti")
    if drop == "train":
        return clean(train, train_id, hit(left, right))
    met = hit(right, left.join(_small(right.select("h").distinct()), "h", "left_semi"))
    if drop == "test":
        return clean(test, test_id, met)
    return clean(train, train_id, hit(left, right)).select(F.lit("train").alias("side"), F.col(train_id).alias("id")).union(clean(test, test_id, met).select(F.lit("test").alias("side"), F.col(test_id).alias("id")))


def decontaminate_chain(train: DataFrame, test: DataFrame, *, train_id: str, test_id: str, n: int = N) -> tuple[DataFrame, DataFrame]:
    """(train, test) kept after three passes: train rows that overlap with test go, then within train and within test all but the first of an overlap."""
    rest = decontaminate(train, test, train_id=train_id, test_id=test_id, n=n)
    one = lambda df, c: _of(df, c, dedup(df, c, "text", "first", n).where("kept").select("id"))
    return one(rest, train_id), one(test, test_id)


def exact_dedup(df: DataFrame, id_column: str, text: str) -> DataFrame:
    """The lowest id of each distinct text; the digest is what is shuffled."""
    return df.groupBy(F.sha2(F.col(text), 256).alias("digest")).agg(F.min(id_column).alias(id_column), F.count("*").alias("copies")).select(id_column, "copies")


def repeated_grams(df: DataFrame, id_column: str, text: str, n: int = N) -> DataFrame:
    """id, h of rows that share a fingerprint with another row: a superset of the grams that two rows have."""
    prints = cut(fingerprints(df, id_column, text, n))  # a sixth of the grams; read twice
    twice = cut(prints.groupBy("f").agg(F.min("id").alias("low"), F.max("id").alias("high")).where("low < high").select("f"))
    ids = cut(prints.join(_small(twice), "f", "left_semi").select("id").distinct())
    return distinct_grams(_of(df, id_column, ids), id_column, text, n)


def star_edges(df: DataFrame, id_column: str, text: str, n: int = N) -> DataFrame:
    """id, first: for each gram, every id with it but the lowest, and the lowest. Linear in the rows of a gram, however common it is."""
    g = cut(repeated_grams(df, id_column, text, n))
    least = cut(g.groupBy("h").agg(F.min("id").alias("first"), F.max("id").alias("last")).where("last > first").select("h", "first"))
    return g.join(_small(least), "h").where("id > first").select("id", "first").distinct()


def components(edges: DataFrame, rounds: int = 50) -> DataFrame:
    """id, component: labels spread along edges and jump to their label's label until none changes."""
    both = cut(edges.select(F.col("id").alias("x"), F.col("first").alias("y")).union(edges.select("first", "id")).distinct())
    label = cut(both.groupBy("x").agg(F.least(F.min("y"), F.col("x")).alias("c")))
    for _ in range(rounds):
        near = both.join(label.withColumnRenamed("x", "y"), "y").groupBy("x").agg(F.min("c").alias("m"))
        new = label.join(near, "x").select("x", F.least("c", "m").alias("c"), F.col("c").alias("old"))
        jump = new.alias("n").join(label.select(F.col("x").alias("k"), F.col("c").alias("cc")), F.col("n.c") == F.col("k"), "left")
        new = cut(jump.select("x", F.least("n.c", F.coalesce("cc", "n.c")).alias("c"), "old"))
        moved = new.where("c <> old").limit(1).count()
        label = new.select("x", "c")
        if not moved:
            return label.select(F.col("x").alias("id"), F.col("c").alias("component"))
    raise RuntimeError("components not stable")


def dedup(df: DataFrame, id_column: str, text: str, mode: str = "first", n: int = N) -> DataFrame:
    """id, kept of a set. first: dropped if any lower id shares a gram. component: one of each connected group.
    greedy: dropped if a lower kept id shares a gram."""
    ids = df.select(F.col(id_column).alias("id"))
    if mode == "first":
        gone = star_edges(df, id_column, text, n).select("id").distinct()
        return ids.join(gone.withColumn("hit", F.lit(True)), "id", "left").select("id", F.col("hit").isNull().alias("kept"))
    if mode == "component":
        part = components(star_edges(df, id_column, text, n))
        return ids.join(part, "id", "left").select("id", (F.col("component").isNull() | (F.col("component") == F.col("id"))).alias("kept"))
    if mode != "greedy":
        raise ValueError(mode)
    g = cut(repeated_grams(df, id_column, text, n))
    shared = g.groupBy("h").agg(F.count("*").alias("c")).where("c > 1").select("h")
    g = cut(g.join(shared, "h"))
    kept, gone = None, None
    open_ = g
    while open_.limit(1).count():  # rows that are least in all their grams are kept; what shares a gram with a kept row goes
        least = open_.groupBy("h").agg(F.min("id").alias("low"))
        now = open_.join(least, "h").groupBy("id").agg(F.bool_and(F.col("id") == F.col("low")).alias("first")).where("first").select("id")
        now = cut(now)
        hit = g.join(now, "id", "left_semi").select("h").distinct()
        out = cut(open_.join(hit, "h", "left_semi").select("id").distinct().join(now, "id", "left_anti"))
        kept = now if kept is None else kept.union(now)
        gone = out if gone is None else gone.union(out)
        open_ = cut(open_.join(now.union(out), "id", "left_anti"))
    if gone is None:
        return ids.withColumn("kept", F.lit(True))
    return ids.join(gone.withColumn("hit", F.lit(True)), "id", "left").select("id", F.col("hit").isNull().alias("kept"))


def longest_run(pairs: DataFrame, a: DataFrame, b: DataFrame, *, a_id: str, b_id: str, a_text: str = "text", b_text: str = "text", n: int = N) -> DataFrame:
    """Longest run of shared tokens of each pair: islands of matching grams on one diagonal."""
    from pyspark.sql.window import Window

    left = grams(a.join(pairs.select(a_id).distinct(), a_id, "left_semi"), a_id, a_text, n).select(F.col("id").alias(a_id), F.col("pos").alias("p"), "h")
    right = grams(b.join(pairs.select(b_id).distinct(), b_id, "left_semi"), b_id, b_text, n).select(F.col("id").alias(b_id), F.col("pos").alias("q"), "h")
    hits = left.join(right, "h").join(pairs, [a_id, b_id], "left_semi").withColumn("diagonal", F.col("p") - F.col("q"))
    lane = Window.partitionBy(a_id, b_id, "diagonal").orderBy("p")
    island = hits.withColumn("island", F.col("p") - F.row_number().over(lane))
    runs = island.groupBy(a_id, b_id, "diagonal", "island").agg(F.count("*").alias("m"))
    return runs.groupBy(a_id, b_id).agg((F.max("m") + n - 1).alias("tokens"))
