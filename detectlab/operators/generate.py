"""Answers, the filters on them, correction with hints, and the training records made of them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from detectlab.functions import simulate
from detectlab.functions.tokens import held
from detectlab.sources.tables import cut

LENGTH_CUT = 32_000


def respond(samples: DataFrame, models=simulate.TEACHERS, n: int = 8, *, hinted: bool = False) -> DataFrame:
    """n simulated answers of each model to each labelled sample. Narrow: the model table is a literal."""
    spark = samples.sparkSession
    table = spark.sql(f"SELECT * FROM {simulate.model_values(models)}")
    out = samples.where("is_vuln IS NOT NULL").select("sample_id", "lang", "cwe", "cls", "is_vuln", "n_tokens", "split", "ood_cwe", "ood_lang")
    out = out.crossJoin(F.broadcast(table)).select("*", F.explode(F.sequence(F.lit(1), F.lit(n))).alias("attempt"))
    for name, e in simulate.answer_columns(hinted=hinted).items():
        out = out.withColumn(name, F.expr(e))
    return out.withColumn("hinted", F.lit(hinted))


def attempts_sql(models=simulate.TEACHERS, n: int = 8, *, hinted: bool = False, name: str = "attempt_log", where: str = "TRUE") -> str:
    cols = simulate.answer_columns(sql=True, hinted=hinted)
    inner = f"SELECT sample_id, lang, cwe, cls, is_vuln, n_tokens, split, ood_cwe, ood_lang, m.*, attempt FROM sample, {simulate.model_values(models)}, range(1, {n + 1}) r(attempt) WHERE is_vuln IS NOT NULL AND ({where})"
    for c, e in cols.items():
        inner = f"SELECT *, {e} AS {c} FROM ({inner})"
    return f"{name} AS (SELECT *, {str(hinted).lower()} AS hinted FROM ({inner}))"


def length_filter(attempts: DataFrame, cap: int = LENGTH_CUT, inclusive: bool = False) -> DataFrame:
    """Answers whose prompt and output fit; inclusive: a total of exactly cap is cut too."""
    return attempts.where(F.col("total_tokens") < cap if inclusive else F.col("total_tokens") <= cap)


def truth(cls: str = "cls", vuln: str = "is_vuln") -> Column:
    return F.when(F.col(vuln), F.concat(F.lit("CWE-"), F.col(cls).cast("string"))).otherwise("benign")


def right(attempts: DataFrame) -> DataFrame:
    return attempts.where(F.col("verdict") == truth())


def reject(attempts: DataFrame, *, per_teacher: bool = True, mode: str = "shortest", cap: int = LENGTH_CUT, inclusive: bool = False) -> DataFrame:
    """Rejection sampling: the shortest right answer of each sample (and teacher). mode 'none': the first answer, right or not.

    One aggregation with partial sums: the kept row is the least struct, no window and no sort.
    """
    keys = ["sample_id", "model"] if per_teacher else ["sample_id"]
    rows = attempts if mode == "none" else right(length_filter(attempts, cap, inclusive))
    order = ["attempt", "model"] if mode == "none" else ["out_tokens", "attempt", "model"]
    rest = [c for c in ("out_tokens", "attempt", "model", "verdict", "hinted", "n_tokens", "cwe") if c not in order and c not in keys]
    picked = rows.groupBy(*keys).agg(F.min(F.struct(*[c for c in order if c not in keys], *rest)).alias("k"))
    return picked.select(*keys, "k.*")


def unsolved(attempts: DataFrame, *, scope: str = "any_teacher", cap: int = LENGTH_CUT) -> DataFrame:
    """Samples none of whose answers is right and within the cut (scope 'per_teacher': of a teacher's)."""
    keys = ["sample_id"] if scope == "any_teacher" else ["sample_id", "model"]
    ok = (F.col("verdict") == truth()) & (F.col("total_tokens") <= cap)
    return attempts.groupBy(*keys).agg(F.bool_or(F.coalesce(ok, F.lit(False))).alias("solved")).where("NOT solved").select(*keys)


def failure_census(attempts: DataFrame) -> DataFrame:
    """Unsolved samples of each class, most first: where hints are worth writing."""
    per = attempts.select("sample_id", F.coalesce("cwe", F.lit("none")).alias("cwe")).distinct().join(unsolved(attempts), "sample_id", "left_semi")
    return per.groupBy("cwe").agg(F.count("*").alias("unsolved")).select("cwe", "unsolved", F.rank().over(Window.orderBy(F.desc("unsolved"))).alias("rank"))


def hints(spark, n_classes: int = 19) -> DataFrame:
    """Hints of each class: literal rows, 73 for 19 classes."""
    return spark.sql(
        f"SELECT concat('CWE-', c) AS cwe, h AS hint_no, concat('For class ', c, ': ', element_at(array('trace where the input comes from', 'check the bounds before use', 'confirm what the caller may hold', 'look for a path around the check'), h)) AS text "
        f"FROM (SELECT explode(sequence(0, {n_classes - 1})) AS c) LATERAL VIEW explode(sequence(1, 4 - CASE WHEN c < 3 THEN 1 ELSE 0 END)) AS h"
    )


HINTS_SQL = """
hints AS (
  SELECT 'CWE-' || c AS cwe, h AS hint_no, 'For class ' || c || ': ' || ['trace where the input comes from', 'check the bounds before use', 'confirm what the caller may hold', 'look for a path around the check'][h] AS text
  FROM range(0, 19) a(c), range(1, 5) b(h) WHERE h <= 4 - CASE WHEN c < 3 THEN 1 ELSE 0 END)"""


def correct(samples: DataFrame, attempts: DataFrame, hint_rows: DataFrame, *, models=simulate.TEACHERS, n: int = 8, only_hinted_classes: bool = False) -> DataFrame:
    """Asks again for unsolved samples, with the hints of their class in the prompt, and rejects again."""
    again = samples.join(unsolved(attempts), "sample_id", "left_semi")
    per = hint_rows.groupBy("cwe").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("hint_no", "text"))), lambda x: x.text), "; ").alias("hint"))
    if only_hinted_classes:
        again = again.join(F.broadcast(per), "cwe", "left_semi")
    picked = reject(respond(again, models, n, hinted=True), per_teacher=False)
    return picked.join(F.broadcast(per), "cwe", "left")  # hints are a bounded hand-written table


def build_prompt(samples: DataFrame, *, system: str = "You judge code.", shots: int = 0, hint: Column | None = None, policy: Column | None = None, budget: int | None = None) -> DataFrame:
    """sample_id, prompt: system line, step-wise instruction, what is asked for, then the code."""
    parts = [F.lit(system), F.lit("Think step by step.")]
    if budget:
        parts.append(F.lit(f"Reason within {budget} tokens."))
    if policy is not None:
        parts.append(F.concat(F.lit("Choose among: "), F.array_join(policy, ", ")))
    if hint is not None:
        parts.append(hint)
    if shots:
        parts.append(F.col("shots"))
    return samples.select("sample_id", F.concat_ws("\n", *parts, F.lit("Code:"), F.col("code")).alias("prompt"))


def pick_shots(samples: DataFrame, pool: DataFrame, k: int = 3) -> DataFrame:
    """sample_id, shots: the k rows of pool nearest in n_tokens, then by sample_id, of the same language; fewer if the language has fewer, an empty array if it has none.

    A sample must not be in pool. Only sizes are ordered, each with its first k rows: those of k sizes at or below and k above hold the nearest.
    """
    size = ["lang", "n_tokens"]
    known = F.col("lang").isNotNull() & F.col("n_tokens").isNotNull()
    first = pool.where(known).withColumn("rk", F.row_number().over(Window.partitionBy(*size).orderBy("sample_id"))).where(F.col("rk") <= k)
    held_ = first.groupBy(*size).agg(F.collect_list("sample_id").alias("ids"))
    ranked = held_.select("lang", F.col("n_tokens").alias("m"), "ids", F.row_number().over(Window.partitionBy("lang").orderBy("n_tokens")).alias("place"))
    wanted = samples.where(known).select(*size).distinct()
    marks = wanted.select(*size, F.lit(0).alias("one")).union(held_.select(*size, F.lit(1)))
    upto = marks.groupBy(*size).agg(F.sum("one").alias("one")).withColumn("place", F.sum("one").over(Window.partitionBy("lang").orderBy("n_tokens")))
    near = wanted.join(upto, size).select(*size, F.explode(F.sequence(F.col("place") - (k - 1), F.col("place") + k)).alias("place"))
    near = near.join(ranked, ["lang", "place"]).select(*size, F.abs(F.col("m") - F.col("n_tokens")).alias("d"), F.explode("ids").alias("shot"))
    best = F.slice(F.array_sort(F.collect_list(F.struct("d", "shot"))), 1, k)
    shots = near.groupBy(*size).agg(F.transform(best, lambda x: x.shot).alias("shots"))
    none = F.array().cast(f"array<{dict(pool.dtypes)['sample_id']}>")
    return samples.join(shots, size, "left").select("sample_id", F.coalesce("shots", none).alias("shots"))


def chain_text(verdict: str = "verdict") -> Column:
    """A short chain for an answer: repeated steps, one digression, and the final section."""
    steps = F.array_join(F.transform(F.sequence(F.lit(1), F.col("attempt") % 3 + 2), lambda i: F.concat(F.lit("Check the "), F.when(i % 2 == 1, "input").otherwise("bounds"), F.lit("."))), " ")
    final = F.when(F.col(verdict).isNull(), "no idea").when(F.col(verdict) == "benign", "Final Answer: benign").otherwise(F.concat(F.lit("Final Answer: vulnerable "), F.col(verdict)))
    return F.concat(steps, F.lit(" Perhaps CWE-999 applies. "), final)


CHAIN_SQL = """array_to_string(list_transform(range(1, attempt % 3 + 3), lambda i: 'Check the ' || CASE WHEN i % 2 = 1 THEN 'input' ELSE 'bounds' END || '.'), ' ') || ' Perhaps CWE-999 applies. ' ||
  CASE WHEN verdict IS NULL THEN 'no idea' WHEN verdict = 'benign' THEN 'Final Answer: benign' ELSE 'Final Answer: vulnerable ' || verdict END"""

FINAL = r"(?s).*Final Answer:\s*(.*)$"  # the last final section


def parse_answer(df: DataFrame, column: str = "chain") -> DataFrame:
    """Adds said (vulnerable, benign or null), said_classes (array) and said_well: read from the last final section."""
    last = F.regexp_extract(column, FINAL, 1)
    kind = F.regexp_extract(last, r"^(vulnerable|benign)", 1)
    classes = F.when(kind == "vulnerable", F.array_distinct(F.regexp_extract_all(last, F.lit(r"(CWE-[0-9]+)"), 1))).otherwise(F.array().cast("array<string>"))
    well = (kind == "benign") | ((kind == "vulnerable") & (F.size(classes) > 0))
    return df.withColumns({"said": F.when(kind != "", kind), "said_classes": classes, "said_well": well})


def places(df: DataFrame, *order: str, name: str = "place") -> DataFrame:
    """Adds the row's place, from 1, in the whole order. Rows are dealt in ranges of it, numbered in each, and moved by
    the rows of the ranges before: no task holds more than its range."""
    ranged = cut(cut(df).repartitionByRange(*order).withColumn("range_no", F.spark_partition_id()))
    before = Window.orderBy("range_no").rowsBetween(Window.unboundedPreceding, -1)  # a row a range
    moved = ranged.groupBy("range_no").agg(F.count("*").alias("n")).select("range_no", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("moved"))
    inside = F.row_number().over(Window.partitionBy("range_no").orderBy(*order))
    return ranged.join(F.broadcast(moved), "range_no").withColumn(name, inside + F.col("moved")).drop("range_no", "moved")


def condense(records: DataFrame, column: str = "chain") -> DataFrame:
    """Adds condensed: each sentence once, the final section kept."""
    body = F.regexp_extract(column, r"(?s)^(.*?)\s*(?:Final Answer:|$)", 1)
    final = F.regexp_extract(column, r"(?s)(Final Answer:.*)$", 1)
    steps = F.array_distinct(F.filter(F.split(body, r"(?<=\.)\s+"), lambda x: (x != "") & ~x.startswith("Perhaps")))
    return records.withColumn("condensed", F.concat_ws(" ", F.array_join(steps, " "), final))


def stage1(accepted: DataFrame, corrected: DataFrame, samples: DataFrame) -> DataFrame:
    """Records of the first stage: both accepted sets, the prompt built from the sample alone, so no hint can be in it."""
    cols = ["sample_id", "model", "out_tokens", "attempt", "verdict", "hinted"]
    both = accepted.select(*cols).unionByName(corrected.select(*cols)).withColumn("chain", chain_text())
    return both.join(build_prompt(samples), "sample_id").withColumn("stage", F.lit(1))


def curriculum(first: DataFrame, second: DataFrame, seed: int = 7) -> DataFrame:
    """All full chains in a seeded order, then all condensed ones. key orders the export; no global sort is needed to write shards."""
    key = F.pmod(F.col("sample_id") * 7919 + F.col("attempt") * 104729 + seed, F.lit(1_000_003))
    cols = ["sample_id", "model", "attempt", "stage", "prompt", "completion", "tokens"]
    return first.select(*cols).unionByName(second.select(*cols)).withColumn("key", F.col("stage") * 2_000_000 + key)


def pack(records: DataFrame, cap: int = LENGTH_CUT, shards: int = 8) -> DataFrame:
    """Packs by prefix sums in each shard: a record goes to the pack in which its last token falls, so a pack holds the cap and one record's start at most."""
    order = Window.partitionBy("shard").orderBy("key", "sample_id", "model", "stage").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    placed = records.withColumn("shard", F.pmod("sample_id", F.lit(shards))).withColumn("upto", F.sum("tokens").over(order))
    return placed.withColumn("pack", F.expr(f"(upto - 1) div {cap}")).drop("upto")


def repetition(df: DataFrame, column: str, n: int = 3) -> DataFrame:
    """Adds repeated: share of the n-grams of words that occur before, in thousandths."""
    rows = held(df, words_=F.split(F.col(column), r"\s+"))
    last = F.size("words_") - n
    grams = F.transform(F.sequence(F.lit(0), F.greatest(last, F.lit(0))), lambda i: F.array_join(F.slice("words_", i + 1, n), " "))
    rows = held(rows, grams_=grams)
    share = F.floor(1000 * (F.size("grams_") - F.size(F.array_distinct("grams_"))) / F.size("grams_")).cast("int")
    return rows.withColumn("repeated", F.when(last >= 0, share).otherwise(0)).drop("words_", "grams_")
