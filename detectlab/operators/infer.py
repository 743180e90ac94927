"""Inference: cut chains, candidate sets, votes, token use."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

TOKEN_CAP = 8192


def truncate(attempts: DataFrame, budget: int) -> DataFrame:
    """Adds cut, kept_tokens and truncated: the chain's first words, the final marker, then the verdict."""
    words = F.split("chain", r"\s+")
    long = F.size(words) > budget
    verdict = F.coalesce(F.col("verdict"), F.lit("unknown"))
    return attempts.withColumns({"cut": long, "kept_tokens": F.least(F.col("out_tokens"), F.lit(budget)), "truncated": F.when(long, F.concat(F.array_join(F.slice(words, 1, budget), " "), F.lit(" Final Answer: "), verdict)).otherwise(F.col("chain"))})


def policy(attempts: DataFrame, n: int = 4, lo: int = 2, hi: int = 5) -> DataFrame:
    """sample_id, model, policy, votes, padded: candidates of the first n answers by votes then code, hi at most; filled with the next codes up to lo."""
    cand = F.array_distinct(F.array("claim", "second"))
    votes = attempts.where(F.col("attempt") <= n).select("sample_id", "model", F.explode(F.filter(cand, lambda x: x >= 0)).alias("c")).groupBy("sample_id", "model", "c").agg(F.count("*").alias("v"))
    ranked = votes.groupBy("sample_id", "model").agg(F.array_sort(F.collect_list(F.struct((-F.col("v")).alias("v"), "c"))).alias("x"))
    top = F.slice(F.transform("x", lambda s: s.c), 1, hi)
    more = F.array_except(F.transform(F.sequence(F.lit(1), F.lit(lo)), lambda k: (F.element_at(top, -1) + k) % 20), top)
    full = F.when(F.size(top) < lo, F.concat(top, F.slice(more, 1, F.greatest(F.lit(lo) - F.size(top), F.lit(0))))).otherwise(top)
    name = lambda a: F.transform(a, lambda c: F.concat(F.lit("CWE-"), c.cast("string")))
    return ranked.select("sample_id", "model", name(full).alias("policy"), F.size(top).alias("voted"), (F.size(top) < lo).alias("padded"))


def predict_policy(attempts: DataFrame, policies: DataFrame, final: int = 5) -> DataFrame:
    """The answer numbered final, held to the policy: a class outside it becomes benign."""
    one = attempts.where(F.col("attempt") == final).join(policies, ["sample_id", "model"])
    held = F.when(F.col("verdict").isNull() | (F.col("verdict") == "benign") | F.array_contains("policy", F.col("verdict")), F.col("verdict")).otherwise("benign")
    return one.withColumn("verdict", held).drop("policy", "voted", "padded")


def majority(votes: DataFrame, ks: tuple[int, ...] = (1, 4, 8, 16), *, keys: tuple[str, ...] = ("sample_id",), answer: str = "answer") -> DataFrame:
    """keys, k, answer, votes: the most frequent of the first k answers; ties go to the one given first.

    All sizes in one pass: answers are counted once for each k by conditional sums, so nothing is multiplied by the sizes before the shuffle.
    """
    aggs = [F.sum((F.col("attempt") <= k).cast("int")).alias(f"v{k}") for k in ks]
    per = votes.where(F.col("attempt") <= max(ks)).groupBy(*keys, answer).agg(F.min("attempt").alias("first"), *aggs)
    best = per.groupBy(*keys).agg(*[F.max(F.struct(F.col(f"v{k}").alias("votes"), (-F.col("first")).alias("f"), F.col(answer).alias("answer"))).alias(f"b{k}") for k in ks])
    return best.select(*keys, F.inline(F.array(*[F.struct(F.lit(k).alias("k"), F.col(f"b{k}.answer").alias("answer"), F.col(f"b{k}.votes").alias("votes")) for k in ks])))


def token_usage(attempts: DataFrame, cap: int = TOKEN_CAP) -> DataFrame:
    """Mean, median and largest output by model under the cap, and answers cut."""
    used = F.least("out_tokens", F.lit(cap))
    return attempts.groupBy("model").agg(F.avg(used).alias("mean_tokens"), F.percentile(used, 0.5).alias("median_tokens"), F.max(used).alias("most_tokens"), F.sum((F.col("out_tokens") > cap).cast("int")).alias("cut"))


def knn(queries: DataFrame, base: DataFrame, k: int, *, block: int = 256) -> DataFrame:
    """q, rank, b, label: the k nearest rows of base to every query by cosine, the query itself left out.

    The queries are the stated set: they are packed in blocks of bounded size, each block meets every partition
    of base as one matrix product, and a partition hands on its k best of each query.
    """
    import numpy as np
    import pyarrow as pa

    packed = queries.select(F.expr(f"vec_id div {block}").alias("g"), F.struct("vec_id", "embedding").alias("q")).groupBy("g").agg(F.collect_list("q").alias("qs"))

    def run(batches):
        for batch in batches:
            for qs, bs in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                x, y = (np.array([r["embedding"] for r in v], np.float64) for v in (qs, bs))
                x, y = x / np.linalg.norm(x, axis=1, keepdims=True), y / np.linalg.norm(y, axis=1, keepdims=True)
                qi, bi, lab = np.array([r["vec_id"] for r in qs]), np.array([r["vec_id"] for r in bs]), np.array([r["label"] for r in bs])
                s = np.round(x @ y.T, 9)
                s[qi[:, None] == bi[None]] = -9
                order = np.lexsort((np.broadcast_to(bi, s.shape), -s), axis=1)[:, :k]
                keep = np.take_along_axis(s, order, 1) > -9
                rows, cols = np.nonzero(keep)
                o = order[rows, cols]
                yield pa.RecordBatch.from_arrays([pa.array(qi[rows]), pa.array(bi[o]), pa.array(lab[o].astype(np.int32)), pa.array(s[rows, o])], ["q", "b", "label", "score"])

    blocks = base.select(F.expr(f"vec_id div {4 * block}").alias("h"), F.struct("vec_id", "embedding", "label").alias("b")).groupBy("h").agg(F.collect_list("b").alias("bs"))
    near = packed.crossJoin(blocks).select("qs", "bs").mapInArrow(run, "q long, b long, label int, score double")
    w = Window.partitionBy("q").orderBy(F.desc("score"), "b")
    return near.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("q", "rank", "b", "label", "score")
