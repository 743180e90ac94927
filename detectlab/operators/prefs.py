"""Training-side objectives as data: likelihoods, preference pairs, rewards, masks and histories."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from detectlab.functions.tokens import held, tokens
from detectlab.operators.generate import truth

#: Reward levels: right verdict and class, right verdict only, wrong, badly formed.
LEVELS = (1.0, 0.5, 0.0, -1.0)
START, END = "^", "$"


def token_pairs(df: DataFrame, id_column: str, text: str) -> DataFrame:
    """id, prev, next: neighbours in the token row, with a start and an end sign."""
    rows = held(df.select(F.col(id_column).alias("id"), F.col(text).alias("text")), t=F.concat(F.array(F.lit(START)), tokens("text"), F.array(F.lit(END))))
    t = F.col("t")
    return rows.select("id", F.inline(F.arrays_zip(F.slice(t, 1, F.size(t) - 1).alias("prev"), F.slice(t, 2, F.size(t) - 1).alias("next"))))


def fit_bigram(train: DataFrame, id_column: str, text: str) -> DataFrame:
    """prev, next, c, prev_c: counts of neighbours."""
    pairs = token_pairs(train, id_column, text).groupBy("prev", "next").agg(F.count("*").alias("c"))
    return pairs.join(pairs.groupBy("prev").agg(F.sum("c").alias("prev_c")), "prev")


def nll(df: DataFrame, id_column: str, text: str, lm: DataFrame, vocabulary: int) -> DataFrame:
    """id, tokens, nll: negative log likelihood under add-one smoothing. Equal pairs are one row before the join."""
    rows = token_pairs(df, id_column, text).groupBy("id", "prev", "next").agg(F.count("*").alias("times"))
    seen = rows.join(lm.select("prev", "next", "c"), ["prev", "next"], "left")
    total = seen.join(lm.groupBy("prev").agg(F.max("prev_c").alias("prev_c")), "prev", "left")
    p = (F.coalesce("c", F.lit(0)) + 1) / (F.coalesce("prev_c", F.lit(0)) + vocabulary)
    return total.groupBy("id").agg(F.sum("times").alias("tokens"), F.sum(-F.log(p) * F.col("times")).alias("nll"))


def decode(lm: DataFrame, prompt: str, limit: int) -> list[str]:
    """Greedy continuation of one prompt: the most frequent next token (then the first by name), until the end sign or the limit."""
    best = lm.groupBy("prev").agg(F.min(F.struct((-F.col("c")).alias("c"), "next")).alias("b")).select("prev", "b.next")
    out, last = [], prompt
    for _ in range(limit):  # a row a step: the table is bucketed by prev when used at scale
        row = best.where(F.col("prev") == last).first()
        if row is None or row.next == END:
            break
        out.append(row.next)
        last = row.next
    return out


def length_pairs(attempts: DataFrame) -> DataFrame:
    """One pair a sample: its shortest right answer over its longest. sample_id, chosen, rejected (answer numbers), len_gap."""
    good = attempts.where(F.col("verdict") == truth())
    key = F.struct("out_tokens", "model", "attempt")
    name = lambda c: F.concat_ws("/", F.col(f"{c}.model"), F.col(f"{c}.attempt").cast("string"))
    ends = good.groupBy("sample_id").agg(F.min(key).alias("lo"), F.max(key).alias("hi"))
    return ends.where("hi.out_tokens > lo.out_tokens").select("sample_id", name("lo").alias("chosen"), name("hi").alias("rejected"), (F.col("hi.out_tokens") - F.col("lo.out_tokens")).alias("len_gap"))


def dpo_loss(df: DataFrame, beta: float = 0.1) -> DataFrame:
    """Adds loss = -log sigmoid(beta * (chosen - rejected)) of the columns chosen_ratio and rejected_ratio (log ratios to the reference)."""
    margin = F.lit(beta) * (F.col("chosen_ratio") - F.col("rejected_ratio"))
    return df.withColumn("loss", F.greatest(-margin, F.lit(0.0)) + F.log1p(F.exp(-F.abs(margin))))  # no overflow at any margin


def outcome_reward(levels: tuple[float, ...] = LEVELS) -> Column:
    """Reward of an answer: its form, its verdict, its class."""
    said_vuln = F.col("verdict") != "benign"
    return (
        F.when(F.col("verdict").isNull(), levels[3])
        .when(F.col("verdict") == truth(), levels[0])
        .when(said_vuln & F.col("is_vuln"), levels[1])
        .otherwise(levels[2])
    )


def group_advantage(rewards: DataFrame, keys: tuple[str, ...] = ("sample_id", "model")) -> DataFrame:
    """Adds advantage: reward less the group's mean over its standard deviation; 0 where all are equal."""
    w = Window.partitionBy(*keys)
    sd = F.stddev_pop("reward").over(w)
    return rewards.withColumn("advantage", F.coalesce(F.try_divide(F.col("reward") - F.avg("reward").over(w), F.when(sd > 1e-12, sd)), F.lit(0.0)))


def dynamic_groups(rewards: DataFrame, keys: tuple[str, ...] = ("sample_id", "model")) -> DataFrame:
    """Groups that are neither all right nor all wrong."""
    g = rewards.groupBy(*keys).agg(F.count("*").alias("answers"), F.sum((F.col("reward") == LEVELS[0]).cast("int")).alias("right"))
    return g.where("right > 0 AND right < answers")


def lazy_policy_report(rewards: DataFrame, rounds: int = 4) -> DataFrame:
    """By round of answers: share of misses and of 'benign', and mean reward of the answers, of saying benign always, and of the truth."""
    r = rewards.withColumn("round", F.expr(f"(attempt - 1) div {rounds // 2}"))
    vuln = F.col("is_vuln")
    benign = F.col("verdict") == "benign"
    lazy = F.when(vuln, LEVELS[2]).otherwise(LEVELS[0])
    return r.groupBy("model", "round").agg(
        F.sum(F.when(vuln & benign, 1).otherwise(0)).alias("missed"), F.sum(vuln.cast("int")).alias("vulnerable"), F.sum(F.when(benign, 1).otherwise(0)).alias("said_benign"),
        F.count("*").alias("answers"), F.avg("reward").alias("mean_reward"), F.avg(lazy).alias("lazy_reward"))


def loss_mask(turns: DataFrame) -> DataFrame:
    """conv_id, messages: turns in order, learn only those that the model produced."""
    m = F.struct("turn", "role", "text", (F.col("role") == "assistant").alias("learn"))
    return turns.groupBy("conv_id").agg(F.array_sort(F.collect_list(m)).alias("messages"))


def reject_traces(turns: DataFrame, want: Column) -> DataFrame:
    """Turns of traces whose last model turn satisfies want (an expression on its text)."""
    last = turns.where("role = 'assistant'").groupBy("conv_id").agg(F.max_by("text", "turn").alias("text")).where(want).select("conv_id")
    return turns.join(last, "conv_id", "left_semi")


def turn_examples(turns: DataFrame) -> DataFrame:
    """conv_id, turn, history (array of role: text before it), target: one row a model turn."""
    w = Window.partitionBy("conv_id").orderBy("turn").rowsBetween(Window.unboundedPreceding, -1)
    return turns.withColumn("history", F.collect_list(F.concat_ws(": ", "role", "text")).over(w)).where("role = 'assistant'").select("conv_id", "turn", "history", F.col("text").alias("target"))
