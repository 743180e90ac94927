"""Scores. Predictions have sample_id, model, verdict ('benign', a class, or null), truth columns is_vuln and cls, runtime_ms and out_tokens."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from detectlab.operators.generate import truth

MODES = ("strict", "double", "binary")


def cells(mode: str = "strict") -> dict[str, Column]:
    """tp, fp, fn, tn of one prediction. A class named wrongly on a vulnerable sample: strict, a miss; double, a miss and a false alarm; binary, a hit."""
    if mode not in MODES:
        raise ValueError(mode)
    flagged = F.coalesce(F.col("verdict") != "benign", F.lit(False))
    vuln = F.col("is_vuln")
    exact = F.coalesce(F.col("verdict") == truth(), F.lit(False))
    hit = flagged if mode == "binary" else exact
    extra = (vuln & flagged & ~exact) if mode == "double" else F.lit(False)
    one = lambda c: c.cast("int")
    return {"tp": one(vuln & hit), "fp": one(~vuln & flagged) + one(extra), "fn": one(vuln & ~hit), "tn": one(~vuln & ~flagged)}


def confusion(preds: DataFrame, by: tuple[str, ...] = ("model",), mode: str = "strict") -> DataFrame:
    """One hash aggregation with partial sums."""
    return preds.groupBy(*by).agg(*[F.sum(c).alias(name) for name, c in cells(mode).items()])


def rates(counts: DataFrame) -> DataFrame:
    """Adds precision, recall, f1, fpr, fnr; null where there is nothing to divide by."""
    ratio = lambda a, b: F.try_divide(a.cast("double"), b.cast("double"))
    tp, fp, fn, tn = (F.col(c) for c in ("tp", "fp", "fn", "tn"))
    return counts.withColumns({"precision": ratio(tp, tp + fp), "recall": ratio(tp, tp + fn), "f1": F.when(tp + fn > 0, ratio(2 * tp, 2 * tp + fp + fn)), "fpr": ratio(fp, fp + tn), "fnr": ratio(fn, fn + tp)})


RATES_SQL = """tp::DOUBLE / nullif(tp + fp, 0) AS precision, tp::DOUBLE / nullif(tp + fn, 0) AS recall, CASE WHEN tp + fn > 0 THEN 2.0::DOUBLE * tp / nullif(2 * tp + fp + fn, 0) END AS f1,
  fp::DOUBLE / nullif(fp + tn, 0) AS fpr, fn::DOUBLE / nullif(fn + tp, 0) AS fnr"""


def cells_sql(mode: str = "strict") -> str:
    exact = "coalesce(verdict = CASE WHEN is_vuln THEN 'CWE-' || cls ELSE 'benign' END, false)"
    flag = "coalesce(verdict <> 'benign', false)"
    hit = flag if mode == "binary" else exact
    extra = f" + sum((is_vuln AND {flag} AND NOT {exact})::INT)" if mode == "double" else ""
    return f"sum((is_vuln AND {hit})::INT)::BIGINT AS tp, (sum((NOT is_vuln AND {flag})::INT){extra})::BIGINT AS fp, sum((is_vuln AND NOT {hit})::INT)::BIGINT AS fn, sum((NOT is_vuln AND NOT {flag})::INT)::BIGINT AS tn"


def f1_by(preds: DataFrame, by: tuple[str, ...], mode: str = "strict") -> DataFrame:
    return rates(confusion(preds, ("model", *by), mode))


def by_class(preds: DataFrame) -> DataFrame:
    """One against the rest for every class: model, cls, tp, fp, fn. A prediction is a row of its truth and a row of its claim."""
    said = F.when(F.col("verdict").startswith("CWE-"), F.substring("verdict", 5, 9).cast("int"))
    true = F.when(F.col("is_vuln"), F.col("cls"))
    rows = preds.select("model", true.alias("true"), said.alias("said"))
    sides = F.array(F.struct(F.col("true").alias("cls"), F.lit(1).alias("is_true")), F.struct(F.col("said").alias("cls"), F.lit(0).alias("is_true")))
    flat = rows.select("model", (F.col("true") == F.col("said")).alias("same"), F.inline(sides)).where("cls IS NOT NULL")
    same = F.coalesce(F.col("same"), F.lit(False))
    return flat.groupBy("model", "cls").agg(F.sum(((F.col("is_true") == 1) & same).cast("int")).alias("tp"), F.sum(((F.col("is_true") == 0) & ~same).cast("int")).alias("fp"), F.sum(((F.col("is_true") == 1) & ~same).cast("int")).alias("fn"))


def macro_f1(per_class: DataFrame) -> DataFrame:
    """Macro, micro and support-weighted F1 over the classes that have positives."""
    f1 = F.when(F.col("tp") + F.col("fn") > 0, 2.0 * F.col("tp") / (2 * F.col("tp") + F.col("fp") + F.col("fn")))
    n = F.col("tp") + F.col("fn")
    return per_class.groupBy("model").agg(
        F.avg(f1).alias("macro_f1"), F.try_divide(2.0 * F.sum("tp"), 2.0 * F.sum("tp") + F.sum("fp") + F.sum("fn")).alias("micro_f1"), F.try_divide(F.sum(f1 * n), F.sum(n).cast("double")).alias("weighted_f1"), F.count(f1).alias("classes"))


def pareto(df: DataFrame, cost: str, gain: str, key: str = "model") -> DataFrame:
    """Adds on_front: no other row is as cheap and as good, and better in one. For model tables of a few rows."""
    o = df.select(F.col(key).alias("o"), F.col(cost).alias("oc"), F.col(gain).alias("og"))
    worse = df.join(F.broadcast(o), (F.col("oc") <= F.col(cost)) & (F.col("og") >= F.col(gain)) & ((F.col("oc") < F.col(cost)) | (F.col("og") > F.col(gain))), "left_semi").select(key)
    return df.join(worse.withColumn("beaten", F.lit(True)), key, "left").withColumn("on_front", F.col("beaten").isNull()).drop("beaten")


def funnel(stages: dict[str, DataFrame], id_column: str = "sample_id") -> DataFrame:
    """place, stage, rows, samples of each named stage."""
    out = None
    for k, (name, df) in enumerate(stages.items()):
        one = df.agg(F.count("*").alias("rows"), F.countDistinct(id_column).alias("samples")).select(F.lit(k).alias("place"), F.lit(name).alias("stage"), "rows", "samples")
        out = one if out is None else out.union(one)
    return out


def bootstrap(preds: DataFrame, draws: int = 50, seed: int = 3) -> DataFrame:
    """Interval of F1 by model: each sample gets a Poisson weight a draw, from a whole-number hash."""
    spark = preds.sparkSession
    u = (((F.col("sample_id") * 48271 + F.col("draw") * 69621 + seed) % 2147483647) * 16807 % 2147483647) % 1000
    weight = F.when(u < 368, 0).when(u < 736, 1).when(u < 920, 2).when(u < 981, 3).when(u < 996, 4).otherwise(5)  # shares of a Poisson count of mean 1
    rows = preds.crossJoin(F.broadcast(spark.range(draws).withColumnRenamed("id", "draw"))).withColumn("w", weight)
    c = cells()
    per = rows.groupBy("model", "draw").agg(*[F.sum(c[n] * F.col("w")).alias(n) for n in ("tp", "fp", "fn")])
    f1 = F.try_divide(2.0 * F.col("tp"), 2.0 * F.col("tp") + F.col("fp") + F.col("fn"))
    return per.groupBy("model").agg(F.percentile(f1, 0.025).alias("low"), F.percentile(f1, 0.975).alias("high"), F.count("*").alias("draws"))
