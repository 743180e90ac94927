"""What the student is compared with: rule scanners, a slicer, retrieval, fuzzers, bounded flows, and models of given profiles."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from detectlab.functions.tokens import tokens
from detectlab.sources.tables import cut

SYMBOLS = "!#$%&*"
#: Rules up to which they are broadcast (a word each).
RULE_ROWS = 200_000


def learn_rules(train: DataFrame, *, support: int = 2) -> DataFrame:
    """word, support, cls: words of train rows found in vulnerable samples only, with the class they name most.

    train must hold training rows alone: a rule read off test labels would score itself.
    """
    words = train.where("is_vuln IS NOT NULL").select("sample_id", "is_vuln", "cls", F.explode(F.array_distinct(tokens("code"))).alias("word"))
    per = words.groupBy("word").agg(F.sum(F.col("is_vuln").cast("int")).alias("support"), F.sum((~F.col("is_vuln")).cast("int")).alias("benign")).where((F.col("support") >= support) & (F.col("benign") == 0))
    cls = words.where("is_vuln").groupBy("word", "cls").agg(F.count("*").alias("c")).groupBy("word").agg(F.min(F.struct((-F.col("c")).alias("c"), "cls")).alias("m")).select("word", F.col("m.cls").alias("rule_cls"))
    return per.join(cls, "word").select("word", "support", "rule_cls")


def _ready(rules: DataFrame) -> DataFrame:
    """Written once, as a count and a join read them; broadcast up to RULE_ROWS, shuffled by word beyond."""
    rules = cut(rules)
    return F.broadcast(rules) if rules.count() <= RULE_ROWS else rules


def rule_scan(samples: DataFrame, rules: DataFrame, name: str = "rules") -> DataFrame:
    """Predictions: the class of the rule of most support (then first word) found; benign if none."""
    words = samples.select("sample_id", F.explode(F.array_distinct(tokens("code"))).alias("word"))
    best = words.join(_ready(rules), "word").groupBy("sample_id").agg(F.min(F.struct((-F.col("support")).alias("s"), "word", "rule_cls")).alias("b"))
    hit = F.when(F.col("b").isNull(), "benign").otherwise(F.concat(F.lit("CWE-"), F.col("b.rule_cls").cast("string")))
    return samples.join(best, "sample_id", "left").select("sample_id", F.lit(name).alias("model"), hit.alias("verdict"), F.col("b.word").alias("word"))


def form(share: int = 20) -> Column:
    """What the second analyser looks at: 1 for symbols from so many thousandths of the characters on, 2 for brackets that don't pair, 3 for both."""
    symbols = F.length(F.regexp_replace("code", f"[^{SYMBOLS}]", ""))
    opened, closed = F.length(F.regexp_replace("code", r"[^(\[{]", "")), F.length(F.regexp_replace("code", r"[^)\]}]", ""))
    many = F.lit(1000) * symbols >= F.lit(share) * F.greatest(F.length("code"), F.lit(1))
    return F.when(many, 1).otherwise(0) + F.when(opened != closed, 2).otherwise(0)


def learn_structure(train: DataFrame, *, share: int = 20) -> DataFrame:
    """form, rule_cls: the class that vulnerable training rows of each form have most (then the least). Three rows at most."""
    rows = train.where("is_vuln").select(form(share).alias("form"), "cls").where("form > 0")
    return rows.groupBy("form", "cls").agg(F.count("*").alias("c")).groupBy("form").agg(F.min(F.struct((-F.col("c")).alias("c"), "cls")).alias("m")).select("form", F.col("m.cls").alias("rule_cls"))


def structure_scan(samples: DataFrame, learned: DataFrame, *, share: int = 20) -> DataFrame:
    """Predictions of the second analyser: its rules are on form, not words, and name the class learned for the form; benign for others."""
    found = samples.select("sample_id", form(share).alias("form")).join(F.broadcast(learned), "form", "left")
    hit = F.when(F.col("rule_cls").isNull(), "benign").otherwise(F.concat(F.lit("CWE-"), F.col("rule_cls").cast("string")))
    return found.select("sample_id", F.lit("structure").alias("model"), hit.alias("verdict"))


def guard_scan(samples: DataFrame, rules: DataFrame) -> DataFrame:
    """Any listed word flags the sample; no class is named."""
    hit = samples.select("sample_id", F.explode(F.array_distinct(tokens("code"))).alias("word")).join(_ready(rules), "word", "left_semi").select("sample_id").distinct()
    return samples.join(hit.withColumn("hit", F.lit(True)), "sample_id", "left").select("sample_id", F.coalesce("hit", F.lit(False)).alias("flagged"))


def slice_context(samples: DataFrame, source: str, sink: str) -> DataFrame:
    """sample_id, lines, kept, slice: the lines from the first source line to the last sink line after it; whole-row expressions, no explode."""
    lines = F.split("code", "\n")
    numbered = F.transform(lines, lambda x, i: F.struct(i.alias("i"), x.alias("x")))
    first = F.array_min(F.transform(F.filter(numbered, lambda r: r.x.rlike(source)), lambda r: r.i))
    last = F.array_max(F.transform(F.filter(numbered, lambda r: r.x.rlike(sink)), lambda r: r.i))
    inside = F.transform(F.filter(numbered, lambda r: (r.i >= first) & (r.i <= last)), lambda r: r.x)
    ok = first.isNotNull() & last.isNotNull() & (first <= last)
    kept = F.when(ok, inside).otherwise(F.array().cast("array<string>"))
    return samples.select("sample_id", F.size(lines).alias("lines"), F.size(kept).alias("kept"), F.array_join(kept, "\n").alias("slice"))


def fuzz_walks(edges: DataFrame, entries: DataFrame, *, walks: int, steps: int, seeds: DataFrame | None = None) -> DataFrame:
    """entry, walk, step, node: seeded random walks. Out-edges are ranked by name; the step's draw picks one. seeds: start nodes instead of entries."""
    w = Window.partitionBy("src").orderBy("dst")
    ranked = edges.select("src", "dst", (F.row_number().over(w) - 1).alias("k"), F.count("*").over(Window.partitionBy("src")).alias("deg"))
    start = (entries.select("entry", F.col("entry").alias("node")) if seeds is None else seeds).withColumn("walk", F.explode(F.sequence(F.lit(0), F.lit(walks - 1))))
    number = F.expr("cast(substring(node, 2) as bigint)")
    at = start.withColumn("step", F.lit(0))
    out = at
    for s in range(1, steps + 1):
        draw = (number * 48271 + F.substring("entry", 2, 10).cast("bigint") * 69621 + F.col("walk") * 16807 + s * 40692 + 12345) % 2147483647 * 48271 % 2147483647
        at = at.withColumn("draw", draw).join(ranked, F.col("node") == F.col("src")).where(F.col("k") == F.col("draw") % F.col("deg")).select("entry", F.col("dst").alias("node"), "walk", F.lit(s).alias("step"))
        out = out.unionByName(at)
    return out


def bounded_flow(edges: DataFrame, sources: DataFrame, sinks: DataFrame, max_fn: int = 4) -> DataFrame:
    """source, sink, hops: sinks within max_fn functions of a source, at the fewest hops; equal ends are merged at every hop."""
    at = sources.select(F.col("node").alias("source"), F.col("node").alias("at"))
    found = None
    for hop in range(1, max_fn):
        at = at.join(edges, F.col("at") == F.col("src")).select("source", F.col("dst").alias("at")).distinct()
        one = at.join(sinks.select(F.col("node").alias("at")), "at", "left_semi").select("source", F.col("at").alias("sink"), F.lit(hop).alias("hops"))
        found = one if found is None else found.union(one)
    return found.groupBy("source", "sink").agg(F.min("hops").alias("hops"))


def fit_student(train: DataFrame, *, features: int = 1 << 14, with_chain: bool = False, kind: str = "bayes"):
    """A small stand-in student on hashed tokens: naive Bayes or logistic regression on the samples' code (and chain). It learns benign and every class."""
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import LogisticRegression, NaiveBayes
    from pyspark.ml.feature import HashingTF

    model = NaiveBayes(featuresCol="x", labelCol="y") if kind == "bayes" else LogisticRegression(featuresCol="x", labelCol="y", maxIter=15, regParam=0.01)
    rows = student_input(train, with_chain).where("y IS NOT NULL")
    return Pipeline(stages=[HashingTF(inputCol="tokens", outputCol="x", numFeatures=features), model]).fit(rows)


def student_input(samples: DataFrame, with_chain: bool = False) -> DataFrame:
    text = F.concat_ws(" ", "code", "chain") if with_chain else F.col("code")
    return samples.select("sample_id", F.when(F.col("is_vuln"), F.col("cls") + 1).when(~F.col("is_vuln"), 0).cast("double").alias("y"), tokens(text).alias("tokens"))


def student_predict(model, samples: DataFrame, name: str = "student") -> DataFrame:
    """Verdicts from the text alone; the class is the predicted one."""
    out = model.transform(student_input(samples).drop("y"))
    named = F.concat(F.lit("CWE-"), (F.col("prediction").cast("int") - 1).cast("string"))
    return out.select("sample_id", F.lit(name).alias("model"), F.when(F.col("prediction") > 0, named).otherwise("benign").alias("verdict"))
