"""Answers, rejection, hints, training records, preferences and rewards."""

from __future__ import annotations

from pyspark.sql import functions as F

from detectlab.functions.tokens import TOKENS_SQL, tokens
from detectlab.operators import generate as G
from detectlab.operators import prefs as P
from detectlab.plans.registry import Registry
from detectlab.sources.tables import SAMPLE_SQL, load, samples

R = Registry()
S = f"WITH {SAMPLE_SQL}"
TRUE = "CASE WHEN is_vuln THEN 'CWE-' || cls ELSE 'benign' END"
A = f"{S}, {G.attempts_sql()}"
ACC = f"accepted AS (SELECT * FROM attempt_log WHERE verdict = {TRUE} AND total_tokens <= 32000 QUALIFY row_number() OVER (PARTITION BY sample_id, model ORDER BY out_tokens, attempt) = 1)"
UNS = f"unsolved AS (SELECT sample_id FROM attempt_log GROUP BY sample_id HAVING NOT bool_or(coalesce(verdict = {TRUE} AND total_tokens <= 32000, false)))"
AGAIN = f"{G.attempts_sql(hinted=True, name='again_log', where='sample_id IN (SELECT sample_id FROM unsolved)')}, corrected AS (SELECT * FROM again_log WHERE verdict = {TRUE} AND total_tokens <= 32000 QUALIFY row_number() OVER (PARTITION BY sample_id ORDER BY out_tokens, attempt, model) = 1)"


def base(spark, sf):
    return samples(spark, sf, labelled=True)


def log(spark, sf, models=("T1", "T2"), n=8):
    return G.respond(base(spark, sf), models, n)


def corrected(spark, sf):
    return G.correct(base(spark, sf), log(spark, sf), G.hints(spark))


@R.query(f"{A} SELECT sample_id, model, attempt, verdict, out_tokens, total_tokens, well_formed, is_right, runtime_ms FROM attempt_log", name="attempts")
def attempts(spark, sf):
    return log(spark, sf).select("sample_id", "model", "attempt", "verdict", "out_tokens", "total_tokens", "well_formed", "is_right", "runtime_ms")


@R.query(f"{A} SELECT model, count(*) AS answers, count(DISTINCT sample_id) AS samples, count(*) FILTER (verdict = {TRUE}) AS right_answers, sum(out_tokens)::BIGINT AS tokens FROM attempt_log GROUP BY model")
def teacher_attempts(spark, sf):
    return log(spark, sf).groupBy("model").agg(F.count("*").alias("answers"), F.countDistinct("sample_id").alias("samples"), F.count_if(F.col("verdict") == G.truth()).alias("right_answers"), F.sum("out_tokens").alias("tokens"))


@R.query(f"{S} SELECT sample_id, md5('You judge code.' || chr(10) || 'Think step by step.' || chr(10) || 'Reason within 500 tokens.' || chr(10) || 'Choose among: ' || cwe || ', CWE-0' || chr(10) || 'Code:' || chr(10) || code) AS prompt_md5 FROM sample")
def prompts(spark, sf):
    s = samples(spark, sf)
    out = G.build_prompt(s, budget=500, policy=F.array("cwe", F.lit("CWE-0")))
    return out.select("sample_id", F.md5("prompt").alias("prompt_md5"))


_NN = f"t AS (SELECT sample_id, lang, cls, n_tokens, is_vuln, split FROM sample WHERE is_vuln IS NOT NULL)"


@R.query(f"{S}, {_NN} SELECT q.sample_id, coalesce(list(b.sample_id ORDER BY abs(b.n_tokens - q.n_tokens), b.sample_id) FILTER (b.sample_id IS NOT NULL), [])[1:3] AS shots FROM t q LEFT JOIN t b ON b.lang = q.lang AND b.split = 'train' WHERE q.split = 'test' GROUP BY q.sample_id")
def few_shots(spark, sf):
    """The nearest labelled training examples in size, of the same language; none where the language is held out from training."""
    s = base(spark, sf)
    return G.pick_shots(s.where("split = 'test'"), s.where("split = 'train'"))


@R.query(f"{A} SELECT model, count(*) FILTER (total_tokens <= 32000) AS kept, count(*) FILTER (total_tokens < 32000) AS kept_inclusive, count(*) AS answers FROM attempt_log GROUP BY model")
def length_filter(spark, sf):
    a = log(spark, sf)
    n = lambda df, c: df.groupBy("model").agg(F.count("*").alias(c))
    return n(a, "answers").join(n(G.length_filter(a), "kept"), "model").join(n(G.length_filter(a, inclusive=True), "kept_inclusive"), "model")


@R.query(f"""{A}, c AS (SELECT sample_id, model, attempt, {G.CHAIN_SQL} AS chain FROM attempt_log), f AS (SELECT *, regexp_extract(chain, '(?s).*Final Answer:\\s*(.*)$', 1) AS last FROM c),
k AS (SELECT *, regexp_extract(last, '^(vulnerable|benign)', 1) AS kind FROM f)
SELECT sample_id, model, attempt, nullif(kind, '') AS said, CASE WHEN kind = 'vulnerable' THEN list_distinct(regexp_extract_all(last, '(CWE-[0-9]+)', 1)) ELSE [] END AS said_classes, kind = 'benign' OR (kind = 'vulnerable' AND regexp_matches(last, 'CWE-[0-9]+')) AS said_well FROM k""")
def parse_answers(spark, sf):
    a = log(spark, sf).withColumn("chain", G.chain_text())
    return G.parse_answer(a).select("sample_id", "model", "attempt", "said", "said_classes", "said_well")


@R.query(f"{A}, {ACC} SELECT sample_id, model, attempt, out_tokens, verdict FROM accepted")
def reject_shortest(spark, sf):
    return G.reject(log(spark, sf)).select("sample_id", "model", "attempt", "out_tokens", "verdict")


@R.query(f"{A} SELECT sample_id, model, attempt, out_tokens FROM attempt_log WHERE verdict = {TRUE} AND total_tokens <= 32000 QUALIFY row_number() OVER (PARTITION BY sample_id ORDER BY out_tokens, attempt, model) = 1")
def reject_shortest_of_both(spark, sf):
    return G.reject(log(spark, sf), per_teacher=False).select("sample_id", "model", "attempt", "out_tokens")


@R.query(f"{A} SELECT sample_id, model, attempt, verdict, out_tokens FROM attempt_log WHERE attempt = 1")
def ablate_no_reject(spark, sf):
    return G.reject(log(spark, sf), mode="none").select("sample_id", "model", "attempt", "verdict", "out_tokens")


_TEACH = " UNION ALL ".join(f"SELECT '{name}' AS recipe, count(*) AS records, count(DISTINCT sample_id) AS samples, sum(out_tokens)::BIGINT AS tokens FROM attempt_log WHERE attempt = 1 AND {w}" for name, w in (("both", "true"), ("T1 only", "model = 'T1'"), ("T2 only", "model = 'T2'")))


@R.query(f"{A} {_TEACH}")
def ablate_teachers(spark, sf):
    raw = G.reject(log(spark, sf), mode="none")
    out = None
    for name, rows in (("both", raw), ("T1 only", raw.where("model = 'T1'")), ("T2 only", raw.where("model = 'T2'"))):
        one = rows.agg(F.lit(name).alias("recipe"), F.count("*").alias("records"), F.countDistinct("sample_id").alias("samples"), F.sum("out_tokens").alias("tokens"))
        out = one if out is None else out.union(one)
    return out


@R.query(f"{A}, {UNS} SELECT sample_id FROM unsolved")
def unsolved(spark, sf):
    return G.unsolved(log(spark, sf))


@R.query(f"{A} SELECT sample_id, model FROM attempt_log GROUP BY sample_id, model HAVING NOT bool_or(coalesce(verdict = {TRUE} AND total_tokens <= 32000, false))")
def unsolved_per_teacher(spark, sf):
    return G.unsolved(log(spark, sf), scope="per_teacher")


@R.query(f"{A}, {UNS} SELECT s.sample_id, s.cwe FROM sample s JOIN unsolved USING (sample_id)")
def rl_pool(spark, sf):
    """The hard samples that online training starts from."""
    return base(spark, sf).join(G.unsolved(log(spark, sf)), "sample_id", "left_semi").select("sample_id", "cwe")


@R.query(f"{A}, {UNS} SELECT cwe, count(*) AS unsolved, rank() OVER (ORDER BY count(*) DESC)::INT AS rank FROM sample JOIN unsolved USING (sample_id) GROUP BY cwe")
def failure_census(spark, sf):
    return G.failure_census(log(spark, sf))


@R.query(f"{A}, {UNS}, {AGAIN}, {G.HINTS_SQL}, per AS (SELECT cwe, string_agg(text, '; ' ORDER BY hint_no) AS hint FROM hints GROUP BY cwe) SELECT sample_id, model, attempt, out_tokens, hint FROM corrected LEFT JOIN per USING (cwe)")
def hint_correction(spark, sf):
    return corrected(spark, sf).select("sample_id", "model", "attempt", "out_tokens", "hint")


@R.query(f"{A}, {UNS}, {AGAIN}, n AS (SELECT (SELECT count(DISTINCT sample_id) FROM attempt_log WHERE verdict = {TRUE} AND total_tokens <= 32000) AS before, (SELECT count(*) FROM corrected) AS extra) SELECT before, extra, round(extra / before, 6) AS gain FROM n")
def correction_gain(spark, sf):
    before = G.reject(log(spark, sf)).agg(F.countDistinct("sample_id").alias("before"))
    return before.crossJoin(corrected(spark, sf).agg(F.count("*").alias("extra"))).withColumn("gain", F.round(F.col("extra") / F.col("before"), 6))


def first_stage(spark, sf):
    return G.stage1(G.reject(log(spark, sf)), corrected(spark, sf), base(spark, sf))


_STAGE1 = f"{A}, {ACC}, {UNS}, {AGAIN}, both_sets AS (SELECT sample_id, model, attempt, out_tokens, verdict, hinted FROM accepted UNION ALL SELECT sample_id, model, attempt, out_tokens, verdict, hinted FROM corrected)"
_PROMPT = "'You judge code.' || chr(10) || 'Think step by step.' || chr(10) || 'Code:' || chr(10) || code"


@R.query(f"{_STAGE1} SELECT count(*) AS records, count(*) FILTER (hinted) AS hinted, 0::BIGINT AS leaks FROM both_sets")
def hint_leak_check(spark, sf):
    """Prompts of records that hold a hint's text: must be none."""
    texts = [r.text for r in G.hints(spark).collect()]  # the hand-written table
    leak = F.greatest(*[F.col("prompt").contains(t).cast("int") for t in texts])
    return first_stage(spark, sf).agg(F.count("*").alias("records"), F.count_if("hinted").alias("hinted"), F.sum(leak).alias("leaks"))


@R.query(f"{_STAGE1} SELECT b.sample_id, b.model, b.attempt, b.hinted, md5({_PROMPT}) AS prompt_md5, {G.CHAIN_SQL} AS completion FROM both_sets b JOIN sample s USING (sample_id)")
def stage1_records(spark, sf):
    return first_stage(spark, sf).select("sample_id", "model", "attempt", "hinted", F.md5("prompt").alias("prompt_md5"), F.col("chain").alias("completion"))


_COND = """c AS (SELECT *, regexp_extract(chain, '(?s)^(.*?)\\s*(?:Final Answer:|$)', 1) AS body, regexp_extract(chain, '(?s)(Final Answer:.*)$', 1) AS final FROM (SELECT b.*, {chain} AS chain FROM both_sets b)),
e AS (SELECT sample_id, model, attempt, out_tokens, chain, final, list_filter(string_split_regex(replace(body, '. ', '.' || chr(10)), chr(10)), lambda x: x <> '' AND NOT starts_with(x, 'Perhaps')) AS steps FROM c),
d AS (SELECT *, list_filter(steps, lambda x, i: list_position(steps, x) = i) AS once FROM e),
condensed AS (SELECT *, array_to_string(once, ' ') || CASE WHEN final <> '' THEN ' ' || final ELSE ' ' END AS short FROM d)""".replace("{chain}", G.CHAIN_SQL)


@R.query(f"{_STAGE1}, {_COND} SELECT sample_id, model, attempt, short AS condensed FROM condensed")
def condense(spark, sf):
    return G.condense(first_stage(spark, sf)).select("sample_id", "model", "attempt", "condensed")


@R.query(f"{_STAGE1}, {_COND} SELECT count(*) AS records, sum(length(chain))::BIGINT AS full_chars, sum(length(short))::BIGINT AS short_chars, sum(out_tokens)::BIGINT AS full_tokens, sum(out_tokens // 5)::BIGINT AS short_tokens, round(1 - sum(out_tokens // 5) / sum(out_tokens), 6) AS saving FROM condensed")
def condense_ratio(spark, sf):
    """Text and simulated tokens before and after: a condensed chain has a fifth of the tokens by construction."""
    short = F.expr("out_tokens div 5")
    return G.condense(first_stage(spark, sf)).agg(
        F.count("*").alias("records"), F.sum(F.length("chain")).alias("full_chars"), F.sum(F.length("condensed")).alias("short_chars"), F.sum("out_tokens").alias("full_tokens"), F.sum(short).alias("short_tokens"), F.round(1 - F.sum(short) / F.sum("out_tokens"), 6).alias("saving"))


_CUT = "w AS (SELECT sample_id, model, attempt, chain, len(string_split_regex(chain, '\\s+')) AS words FROM (SELECT *, {chain} AS chain FROM attempt_log))".replace("{chain}", G.CHAIN_SQL)


@R.query(f"{A}, {_CUT} SELECT model, count(*) AS chains, count(*) FILTER (words > 8) AS cut, count(*) FILTER (words > 8 OR NOT contains(chain, 'Final Answer:')) AS broken FROM w GROUP BY model")
def ablate_budget_train(spark, sf):
    """The failed recipe of cutting training chains at a budget: chains left without a final section."""
    words = F.split("chain", r"\s+")
    a = log(spark, sf).withColumn("chain", G.chain_text()).withColumn("kept", F.array_join(F.slice(words, 1, 8), " "))
    return a.groupBy("model").agg(F.count("*").alias("chains"), F.count_if(F.size(words) > 8).alias("cut"), F.count_if(~F.col("kept").contains("Final Answer:")).alias("broken"))


def two_stages(spark, sf):
    one = first_stage(spark, sf)
    first = one.select("sample_id", "model", "attempt", F.lit(1).alias("stage"), "prompt", F.col("chain").alias("completion"), F.col("out_tokens").alias("tokens"))
    second = G.condense(one).select("sample_id", "model", "attempt", F.lit(2).alias("stage"), "prompt", F.col("condensed").alias("completion"), F.expr("out_tokens div 5").alias("tokens"))
    return G.curriculum(first, second)


_CURR = f"{_STAGE1}, curr AS (SELECT sample_id, model, attempt, stage, CASE stage WHEN 1 THEN out_tokens ELSE out_tokens // 5 END AS tokens, stage * 2000000 + (sample_id * 7919 + attempt * 104729 + 7) % 1000003 AS key FROM both_sets, (VALUES (1), (2)) v(stage))"


@R.query(f"{_CURR} SELECT sample_id, model, attempt, stage, key, row_number() OVER (ORDER BY key, sample_id, model)::INT AS place FROM curr")
def curriculum(spark, sf):
    return G.places(two_stages(spark, sf).select("sample_id", "model", "attempt", "stage", "key"), "key", "sample_id", "model")


@R.query(f"{_CURR}, p AS (SELECT *, sample_id % 8 AS shard, (sum(tokens) OVER (PARTITION BY sample_id % 8 ORDER BY key, sample_id, model, stage) - 1) // 32000 AS pack FROM curr) SELECT shard, pack::BIGINT AS pack, count(*) AS records, sum(tokens)::BIGINT AS tokens FROM p GROUP BY ALL")
def pack_report(spark, sf):
    return G.pack(two_stages(spark, sf)).groupBy("shard", "pack").agg(F.count("*").alias("records"), F.sum("tokens").alias("tokens"))


@R.query("""WITH w AS (SELECT doc_id, string_split_regex(text, '\\s+') AS ws FROM documents), g AS (SELECT doc_id, unnest(range(1, len(ws) - 1)) AS p, ws FROM w WHERE len(ws) >= 3)
SELECT d.doc_id, coalesce(r, 0)::INT AS repeated FROM documents d LEFT JOIN (SELECT doc_id, (1000 * (count(*) - count(DISTINCT ws[p] || ' ' || ws[p + 1] || ' ' || ws[p + 2])) // count(*))::INT AS r FROM g GROUP BY doc_id) USING (doc_id)""")
def repetition(spark, sf):
    return G.repetition(load(spark, sf, "documents").select("doc_id", "text"), "text").select("doc_id", "repeated")


# ---- objectives

_BI = f"tk AS (SELECT sample_id, list_concat(['^'], {TOKENS_SQL.format('code')}, ['$']) AS t, split FROM sample), pr AS (SELECT sample_id, split, t[p - 1] AS a, t[p] AS b FROM (SELECT *, unnest(range(2, len(t) + 1)) AS p FROM tk)), lm AS (SELECT a, b, count(*) AS c FROM pr WHERE split = 'train' GROUP BY a, b), un AS (SELECT a, sum(c) AS pc FROM lm GROUP BY a)"
VOCABULARY = 50_000


@R.query(f"{S}, {_BI} SELECT sample_id AS id, count(*) AS tokens, round(sum(-ln((coalesce(c, 0) + 1) / (coalesce(pc, 0) + {VOCABULARY}))), 4) AS nll FROM pr LEFT JOIN lm USING (a, b) LEFT JOIN un USING (a) WHERE split = 'test' GROUP BY sample_id")
def bigram_nll(spark, sf):
    s = samples(spark, sf)
    lm = P.fit_bigram(s.where("split = 'train'"), "sample_id", "code")
    return P.nll(s.where("split = 'test'"), "sample_id", "code", lm, VOCABULARY).select("id", "tokens", F.round("nll", 4).alias("nll"))


@R.query()
def greedy_decode(spark, sf):
    lm = P.fit_bigram(samples(spark, sf).where("split = 'train'"), "sample_id", "code").cache()
    rows = [(p, " ".join(P.decode(lm, p, 12))) for p in ("the", "der", "la")]
    return spark.createDataFrame(rows, "prompt string, continuation string")


@R.query(f"{_STAGE1} SELECT b.sample_id, b.model, md5({_PROMPT}) AS prompt_md5, verdict AS completion FROM both_sets b JOIN sample s USING (sample_id)")
def sft_no_reason(spark, sf):
    """Records of the student that says its verdict only."""
    return first_stage(spark, sf).select("sample_id", "model", F.md5("prompt").alias("prompt_md5"), F.col("verdict").alias("completion"))


@R.query(f"{A}, o AS (SELECT sample_id, min(ROW(out_tokens, model, attempt)) AS lo, max(ROW(out_tokens, model, attempt)) AS hi FROM attempt_log WHERE verdict = {TRUE} GROUP BY sample_id) SELECT sample_id, lo[2] || '/' || lo[3] AS chosen, hi[2] || '/' || hi[3] AS rejected, hi[1] - lo[1] AS len_gap FROM o WHERE hi[1] > lo[1]")
def length_pairs(spark, sf):
    return P.length_pairs(log(spark, sf))


@R.query(f"{A}, o AS (SELECT sample_id, min(out_tokens) AS lo, max(out_tokens) AS hi FROM attempt_log WHERE verdict = {TRUE} GROUP BY sample_id HAVING max(out_tokens) > min(out_tokens)) SELECT sample_id, round(ln(1 + exp(-0.1 * ((hi - lo) / 1000.0 - (sample_id % 11)))), 6) AS loss FROM o")
def dpo_loss(spark, sf):
    pairs = P.length_pairs(log(spark, sf)).select("sample_id", (F.col("len_gap") / 1000.0).alias("chosen_ratio"), (F.col("sample_id") % 11).cast("double").alias("rejected_ratio"))
    return P.dpo_loss(pairs, 0.1).select("sample_id", F.round("loss", 6).alias("loss"))


REWARD = f"CASE WHEN verdict IS NULL THEN -1.0 WHEN verdict = {TRUE} THEN 1.0 WHEN verdict <> 'benign' AND is_vuln THEN 0.5 ELSE 0.0 END::DOUBLE"
RW = f"{A}, rw AS (SELECT *, {REWARD} AS reward FROM attempt_log)"


def rewards(spark, sf):
    return log(spark, sf).withColumn("reward", P.outcome_reward())


@R.query(f"{RW} SELECT model, reward, count(*) AS n FROM rw GROUP BY ALL")
def outcome_reward(spark, sf):
    return rewards(spark, sf).groupBy("model", "reward").agg(F.count("*").alias("n"))


@R.query(f"{RW} SELECT sample_id, model, attempt, reward, round(CASE WHEN stddev_pop(reward) OVER w > 1e-12 THEN (reward - avg(reward) OVER w) / stddev_pop(reward) OVER w ELSE 0 END, 6) AS advantage FROM rw WINDOW w AS (PARTITION BY sample_id, model)")
def group_advantage(spark, sf):
    return P.group_advantage(rewards(spark, sf)).select("sample_id", "model", "attempt", "reward", F.round("advantage", 6).alias("advantage"))


@R.query(f"{RW} SELECT sample_id, model, count(*) AS answers, count(*) FILTER (reward = 1) AS \"right\" FROM rw GROUP BY ALL HAVING count(*) FILTER (reward = 1) BETWEEN 1 AND count(*) - 1")
def dynamic_groups(spark, sf):
    return P.dynamic_groups(rewards(spark, sf))


@R.query(f"{RW} SELECT model, (attempt - 1) // 2 AS round, count(*) FILTER (is_vuln AND verdict = 'benign') AS missed, count(*) FILTER (is_vuln) AS vulnerable, count(*) FILTER (verdict = 'benign') AS said_benign, count(*) AS answers, round(avg(reward), 6) AS mean_reward, round(avg(CASE WHEN is_vuln THEN 0.0 ELSE 1.0 END), 6) AS lazy_reward FROM rw GROUP BY ALL")
def lazy_policy(spark, sf):
    return P.lazy_policy_report(rewards(spark, sf)).withColumns({c: F.round(c, 6) for c in ("mean_reward", "lazy_reward")})


@R.query("SELECT conv_id, list({'turn': turn, 'role': role, 'learn': role = 'assistant'} ORDER BY turn) AS messages FROM conversations GROUP BY conv_id")
def loss_mask(spark, sf):
    m = P.loss_mask(load(spark, sf, "conversations"))
    return m.select("conv_id", F.transform("messages", lambda x: F.struct(x.turn.alias("turn"), x.role.alias("role"), x.learn.alias("learn"))).alias("messages"))


@R.query(f"SELECT role, count(*) AS turns, sum(len({TOKENS_SQL.format('text')}))::BIGINT AS tokens, sum(CASE WHEN role = 'assistant' THEN 0 ELSE len({TOKENS_SQL.format('text')}) END)::BIGINT AS masked FROM conversations GROUP BY role")
def masked_token_share(spark, sf):
    flat = P.loss_mask(load(spark, sf, "conversations")).select(F.inline("messages"))
    n = F.size(tokens("text"))
    return flat.groupBy("role").agg(F.count("*").alias("turns"), F.sum(n).alias("tokens"), F.sum(F.when(F.col("learn"), 0).otherwise(n)).alias("masked"))


_GOOD = "good AS (SELECT conv_id FROM (SELECT conv_id, arg_max(text, turn) AS t FROM conversations WHERE role = 'assistant' GROUP BY conv_id) WHERE length(t) % 3 <> 0)"


@R.query(f"WITH {_GOOD} SELECT conv_id, turn FROM conversations SEMI JOIN good USING (conv_id)")
def reject_traces(spark, sf):
    """Traces whose last answer is right; here right stands for a length not divisible by three."""
    return P.reject_traces(load(spark, sf, "conversations"), F.length("text") % 3 != 0).select("conv_id", "turn")


@R.query("""WITH h AS (SELECT *, list(role || ': ' || text) OVER (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS history FROM conversations)
SELECT conv_id, turn, md5(coalesce(array_to_string(history, chr(10)), '')) AS history_md5, md5(text) AS target_md5 FROM h WHERE role = 'assistant'""")
def turn_examples(spark, sf):
    return P.turn_examples(load(spark, sf, "conversations")).select("conv_id", "turn", F.md5(F.array_join("history", "\n")).alias("history_md5"), F.md5("target").alias("target_md5"))


@R.query(f"WITH {_GOOD}, h AS (SELECT *, count(*) OVER (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS before FROM conversations SEMI JOIN good USING (conv_id)) SELECT conv_id, turn, before::INT AS history_turns, len({TOKENS_SQL.format('text')})::INT AS learned FROM h WHERE role = 'assistant'")
def agent_sft(spark, sf):
    """Agent records: right traces only, one example a model turn, its tokens alone learned."""
    kept = P.reject_traces(load(spark, sf, "conversations"), F.length("text") % 3 != 0)
    return P.turn_examples(kept).select("conv_id", "turn", F.size("history").alias("history_turns"), F.size(tokens("target")).alias("learned"))
