"""Inference variants, measures, function-level baselines, and the experiments on them."""

from __future__ import annotations

from pyspark.sql import functions as F

from detectlab.functions import simulate
from detectlab.functions.tokens import TOKENS_SQL, tokens
from detectlab.operators import baselines as B
from detectlab.operators import generate as G
from detectlab.operators import infer as I
from detectlab.operators import metrics as M
from detectlab.plans.registry import Registry
from detectlab.sources.tables import SAMPLE_SQL, VOTE_SQL, load, samples, vote_log

R = Registry()
S = f"WITH {SAMPLE_SQL}"
TRUE = "CASE WHEN is_vuln THEN 'CWE-' || cls ELSE 'benign' END"
ALL = tuple(simulate.MODELS)
STUDENTS = ("student-final", "student-filtered", "student-raw", "student-raw-T1", "student-raw-T2", "student-no-reason")
TEST = "split = 'test'"


def base(spark, sf):
    return samples(spark, sf, labelled=True)


def preds(spark, sf, models=ALL, n=1):
    """Predictions on the test rows: each model's first answer."""
    return G.respond(base(spark, sf).where(TEST), models, n)


def P(models=ALL, n=1, where=TEST):
    return f"{S}, {G.attempts_sql(models, n, where=where)}"


def r6(df, *cols):
    return df.withColumns({c: F.round(c, 6) for c in cols})


RATES = ("precision", "recall", "f1", "fpr", "fnr")
RATE6 = "round(precision, 6) AS precision, round(recall, 6) AS recall, round(f1, 6) AS f1, round(fpr, 6) AS fpr, round(fnr, 6) AS fnr"


def rate_sql(by: str, models=ALL, mode="strict", kind=True) -> str:
    tag = ", 'simulated' AS responder" if kind else ""
    return f"{P(models)}, c AS (SELECT {by}, {M.cells_sql(mode)} FROM attempt_log GROUP BY ALL), r AS (SELECT *, {M.RATES_SQL} FROM c) SELECT {by}, tp, fp, fn, tn, {RATE6}{tag} FROM r"


def rate_df(df, by, mode="strict", kind="simulated"):
    return r6(M.f1_by(df, by, mode), *RATES).withColumn("responder", F.lit(kind))


# ---- inference


@R.query(f"{P(('student-final',))} SELECT sample_id, verdict FROM attempt_log")
def predict_direct(spark, sf):
    return preds(spark, sf, ("student-final",)).select("sample_id", "verdict")


_TR = f"w AS (SELECT *, string_split_regex(chain, '\\s+') AS ws FROM (SELECT *, {G.CHAIN_SQL} AS chain FROM attempt_log))"


@R.query(f"{P(('T1',))}, {_TR} SELECT sample_id, len(ws) > 8 AS cut, least(out_tokens, 8)::INT AS kept_tokens, CASE WHEN len(ws) > 8 THEN array_to_string(ws[1:8], ' ') || ' Final Answer: ' || coalesce(verdict, 'unknown') ELSE chain END AS truncated FROM w")
def truncated(spark, sf):
    return I.truncate(preds(spark, sf, ("T1",)).withColumn("chain", G.chain_text()), 8).select("sample_id", "cut", "kept_tokens", "truncated")


BUDGETS = (200, 1000, 5000, 20000, 40000)


@R.query(f"{P(('T1', 'student-final'))}, b AS (SELECT *, CASE WHEN out_tokens > budget AND ({simulate.draw('sample_id', 't', 'budget', 11, True)}) % 1000 < 300 THEN NULL ELSE verdict END AS v FROM attempt_log, (VALUES {', '.join(f'({x})' for x in BUDGETS)}) z(budget)), c AS (SELECT model, budget, sum(least(out_tokens, budget))::BIGINT AS tokens, {M.cells_sql().replace('verdict', 'v')} FROM b GROUP BY ALL) SELECT model, budget, tokens, tp, fp, fn, tn, round(CASE WHEN tp + fn > 0 THEN 2.0::DOUBLE * tp / (2 * tp + fp + fn) END, 6) AS f1 FROM c")
def budget_sweep(spark, sf):
    """Tokens against F1 over cut lengths. A cut answer loses its verdict at a simulated rate."""
    budgets = spark.createDataFrame([(b,) for b in BUDGETS], "budget int")
    p = preds(spark, sf, ("T1", "student-final")).crossJoin(F.broadcast(budgets))
    lost = (F.col("out_tokens") > F.col("budget")) & (F.expr(simulate.draw("sample_id", "t", "budget", 11)) % 1000 < 300)
    p = p.withColumns({"verdict": F.when(~lost, F.col("verdict")), "used": F.least("out_tokens", "budget")})
    out = M.f1_by(p, ("budget",)).join(p.groupBy("model", "budget").agg(F.sum("used").alias("tokens")), ["model", "budget"])
    return r6(out, "f1").select("model", "budget", "tokens", "tp", "fp", "fn", "tn", "f1")


def policy_sql(n: int) -> str:
    return f"""cand AS (SELECT sample_id, model, unnest(list_distinct(list_filter([claim, second], lambda x: x >= 0))) AS c FROM attempt_log WHERE attempt <= {n}),
v AS (SELECT sample_id, model, c, count(*) AS v FROM cand GROUP BY ALL), top AS (SELECT sample_id, model, list(c ORDER BY v DESC, c)[1:5] AS t FROM v GROUP BY ALL),
pol AS (SELECT sample_id, model, list_transform(CASE WHEN len(t) < 2 THEN list_append(t, (t[-1] + 1) % 20) ELSE t END, lambda c: 'CWE-' || c) AS policy, len(t)::INT AS voted, len(t) < 2 AS padded FROM top)"""


PM = ("student-final", "T1")


@R.query(f"{P(PM, 5)}, {policy_sql(4)} SELECT * FROM pol")
def policy_set(spark, sf):
    return I.policy(preds(spark, sf, PM, 5))


_HELD = f"one AS (SELECT a.*, CASE WHEN verdict IS NULL OR verdict = 'benign' OR list_contains(policy, verdict) THEN verdict ELSE 'benign' END AS held FROM attempt_log a JOIN pol USING (sample_id, model) WHERE attempt = 5)"


@R.query(f"{P(PM, 5)}, {policy_sql(4)}, {_HELD} SELECT sample_id, model, held AS verdict FROM one")
def predict_policy(spark, sf):
    a = preds(spark, sf, PM, 5)
    return I.predict_policy(a, I.policy(a)).select("sample_id", "model", "verdict")




def _sweep_sql() -> str:
    parts = []
    for n in (1, 2, 4, 8):
        ctes = policy_sql(n)
        parts.append(f"SELECT * FROM (WITH {ctes} SELECT {n} AS runs, p.model, round(avg(len(policy)), 6) AS mean_size, count(*) FILTER (is_vuln AND list_contains(policy, 'CWE-' || cls)) AS hits, count(*) FILTER (is_vuln) AS vulnerable FROM pol p JOIN sample USING (sample_id) GROUP BY p.model)")
    return f"{P(PM, 8)} " + " UNION ALL ".join(parts)


@R.query(_sweep_sql())
def policy_sweep(spark, sf):
    a, s = preds(spark, sf, PM, 8), base(spark, sf).select("sample_id", "is_vuln", "cls")
    out = None
    for n in (1, 2, 4, 8):
        p = I.policy(a, n).join(s, "sample_id")
        hit = F.col("is_vuln") & F.array_contains("policy", F.concat(F.lit("CWE-"), F.col("cls").cast("string")))
        one = p.groupBy("model").agg(F.round(F.avg(F.size("policy")), 6).alias("mean_size"), F.count_if(hit).alias("hits"), F.count_if("is_vuln").alias("vulnerable")).select(F.lit(n).alias("runs"), "*")
        out = one if out is None else out.union(one)
    return out


@R.query(f"{P(PM, 5)}, {policy_sql(4)}, {_HELD}, k AS (SELECT model, sum(out_tokens)::BIGINT AS all_tokens, sum(out_tokens) FILTER (attempt = 1)::BIGINT AS one_tokens FROM attempt_log GROUP BY model) SELECT model, count(*) FILTER (is_vuln AND list_contains(policy, 'CWE-' || cls)) AS hits, count(*) FILTER (is_vuln) AS vulnerable, all_tokens, one_tokens, round(all_tokens / one_tokens, 6) AS cost FROM pol JOIN sample USING (sample_id) JOIN k USING (model) GROUP BY model, all_tokens, one_tokens")
def policy_report(spark, sf):
    """How often the truth is in the set, and the tokens spent against one answer's."""
    a, s = preds(spark, sf, PM, 5), base(spark, sf).select("sample_id", "is_vuln", "cls")
    p = I.policy(a).join(s, "sample_id")
    hit = F.col("is_vuln") & F.array_contains("policy", F.concat(F.lit("CWE-"), F.col("cls").cast("string")))
    cost = a.groupBy("model").agg(F.sum("out_tokens").alias("all_tokens"), F.sum(F.when(F.col("attempt") == 1, F.col("out_tokens"))).alias("one_tokens"))
    return p.groupBy("model").agg(F.count_if(hit).alias("hits"), F.count_if("is_vuln").alias("vulnerable")).join(cost, "model").withColumn("cost", F.round(F.col("all_tokens") / F.col("one_tokens"), 6))


def votes_sql(table: str, key: str, answer: str, extra: str = "") -> str:
    return f"""ks(k) AS (VALUES (1), (4), (8), (16)), n AS (SELECT {key}, k, {answer} AS answer, count(*) AS votes, min(attempt) AS f FROM {table}, ks WHERE attempt <= k GROUP BY ALL),
win AS (SELECT {key}, k, answer, votes FROM n QUALIFY row_number() OVER (PARTITION BY {key}, k ORDER BY votes DESC, f) = 1)"""


@R.query(f"WITH {VOTE_SQL}, {votes_sql('vote', 'sample_id', 'answer')} SELECT * FROM win")
def majority_vote(spark, sf):
    return I.majority(vote_log(spark, sf))


@R.query(f"WITH {VOTE_SQL}, {votes_sql('vote', 'sample_id', 'answer')} SELECT k, count(*) AS samples, count(*) FILTER (answer = truth) AS hits, round(count(*) FILTER (answer = truth) / count(*), 6) AS accuracy FROM win JOIN (SELECT DISTINCT sample_id, truth FROM vote) USING (sample_id) GROUP BY k")
def vote_curve(spark, sf):
    log = vote_log(spark, sf)
    won = I.majority(log).join(log.select("sample_id", "truth").distinct(), "sample_id")
    return won.groupBy("k").agg(F.count("*").alias("samples"), F.count_if(F.col("answer") == F.col("truth")).alias("hits")).withColumn("accuracy", F.round(F.col("hits") / F.col("samples"), 6))


VM = ("student-final", "base")


@R.query(f"{P(VM, 16)}, a AS (SELECT *, coalesce(verdict, 'none') AS said FROM attempt_log), {votes_sql('a', 'sample_id, model', 'said')}, j AS (SELECT win.*, is_vuln, cls, nullif(answer, 'none') AS verdict FROM win JOIN sample USING (sample_id)), c AS (SELECT model, k, {M.cells_sql()} FROM j GROUP BY ALL), r AS (SELECT *, {M.RATES_SQL} FROM c) SELECT model, k, tp, fp, fn, tn, {RATE6}, 'simulated' AS responder FROM r")
def vote_scaling(spark, sf):
    """F1 of the majority of 1, 4, 8 and 16 answers."""
    a = preds(spark, sf, VM, 16).withColumn("said", F.coalesce("verdict", F.lit("none")))
    won = I.majority(a, keys=("sample_id", "model"), answer="said").withColumn("verdict", F.nullif("answer", F.lit("none")))
    return rate_df(won.join(base(spark, sf).select("sample_id", "is_vuln", "cls"), "sample_id"), ("k",))


@R.query(f"{P(ALL)} SELECT model, round(avg(least(out_tokens, 8192)), 6) AS mean_tokens, quantile_cont(least(out_tokens, 8192), 0.5)::DOUBLE AS median_tokens, max(least(out_tokens, 8192)) AS most_tokens, count(*) FILTER (out_tokens > 8192) AS cut FROM attempt_log GROUP BY model")
def token_usage(spark, sf):
    return r6(I.token_usage(preds(spark, sf)), "mean_tokens")


@R.query(f"SELECT role, count(*) AS turns, round(avg(least(len({TOKENS_SQL.format('text')}), 8192)), 6) AS mean_tokens FROM conversations GROUP BY role")
def token_usage_conversations(spark, sf):
    n = F.least(F.size(tokens("text")), F.lit(I.TOKEN_CAP))
    return load(spark, sf, "conversations").groupBy("role").agg(F.count("*").alias("turns"), F.round(F.avg(n), 6).alias("mean_tokens"))


# ---- measures


def _mode_query(mode):
    @R.query(rate_sql("model", mode=mode), name="confusion" if mode == "strict" else f"confusion_{mode}")
    def run(spark, sf):
        return rate_df(preds(spark, sf), (), mode)


for _mode in M.MODES:
    _mode_query(_mode)


def _group_query(name, *by):
    @R.query(rate_sql(", ".join(("model", *by))), name=name)
    def run(spark, sf):
        return rate_df(preds(spark, sf), by)


for _name, _by in {"f1_by_lang": ("lang",), "f1_by_class": ("cwe",), "ood_report": ("ood_cwe", "ood_lang"), "ood_class_gap": ("ood_cwe",), "ood_language": ("ood_lang",)}.items():
    _group_query(_name, *_by)


@R.query(f"{P()}, c AS (SELECT model, {M.cells_sql()} FROM attempt_log GROUP BY ALL) SELECT model, round(fp::DOUBLE / nullif(fp + tn, 0), 6) AS fpr, round(fn::DOUBLE / nullif(fn + tp, 0), 6) AS fnr FROM c")
def error_rates(spark, sf):
    return r6(M.f1_by(preds(spark, sf), ()), "fpr", "fnr").select("model", "fpr", "fnr")


_CLS = "x AS (SELECT model, CASE WHEN is_vuln THEN cls END AS tr, CASE WHEN starts_with(verdict, 'CWE-') THEN substr(verdict, 5)::INT END AS sd FROM attempt_log), y AS (SELECT model, tr AS cls, 1 AS t, coalesce(tr = sd, false) AS same FROM x UNION ALL SELECT model, sd, 0, coalesce(tr = sd, false) FROM x), pc AS (SELECT model, cls, count(*) FILTER (t = 1 AND same) AS tp, count(*) FILTER (t = 0 AND NOT same) AS fp, count(*) FILTER (t = 1 AND NOT same) AS fn FROM y WHERE cls IS NOT NULL GROUP BY ALL), pf AS (SELECT *, CASE WHEN tp + fn > 0 THEN 2.0::DOUBLE * tp / (2 * tp + fp + fn) END AS f1 FROM pc)"


@R.query(f"{P()}, {_CLS} SELECT model, round(avg(f1), 6) AS macro_f1, round(2.0::DOUBLE * sum(tp) / nullif(2 * sum(tp) + sum(fp) + sum(fn), 0), 6) AS micro_f1, round(sum(f1 * (tp + fn)) / nullif(sum(tp + fn), 0), 6) AS weighted_f1, count(f1) AS classes FROM pf GROUP BY model")
def macro_f1(spark, sf):
    return r6(M.macro_f1(M.by_class(preds(spark, sf))), "macro_f1", "micro_f1", "weighted_f1")


_RT = f"c AS (SELECT model, avg(runtime_ms) AS ms, {M.cells_sql()} FROM attempt_log GROUP BY model), f AS (SELECT model, round(ms, 6) AS mean_ms, round(CASE WHEN tp + fn > 0 THEN 2.0::DOUBLE * tp / (2 * tp + fp + fn) END, 6) AS f1 FROM c)"


def runtime(spark, sf):
    p = preds(spark, sf)
    return r6(M.f1_by(p, ()).join(p.groupBy("model").agg(F.avg("runtime_ms").alias("mean_ms")), "model"), "f1", "mean_ms").select("model", "mean_ms", "f1")


@R.query(f"{P()}, {_RT} SELECT *, 'simulated' AS responder FROM f")
def runtime_f1(spark, sf):
    return runtime(spark, sf).withColumn("responder", F.lit("simulated"))


@R.query(f"{P()}, {_RT} SELECT f.*, NOT EXISTS (SELECT 1 FROM f o WHERE o.mean_ms <= f.mean_ms AND o.f1 >= f.f1 AND (o.mean_ms < f.mean_ms OR o.f1 > f.f1)) AS on_front FROM f")
def pareto(spark, sf):
    return M.pareto(runtime(spark, sf), "mean_ms", "f1")


@R.query(f"{P(('student-filtered', 'student-final'))} SELECT sum(out_tokens) FILTER (model = 'student-filtered')::BIGINT AS before, sum(out_tokens) FILTER (model = 'student-final')::BIGINT AS after, round(1 - sum(out_tokens) FILTER (model = 'student-final') / sum(out_tokens) FILTER (model = 'student-filtered'), 6) AS saving FROM attempt_log")
def token_saving(spark, sf):
    """Output tokens with and without the condensed stage. The rates are inputs of the simulation."""
    p = preds(spark, sf, ("student-filtered", "student-final"))
    of = lambda m: F.sum(F.when(F.col("model") == m, F.col("out_tokens")))
    return p.agg(of("student-filtered").alias("before"), of("student-final").alias("after")).withColumn("saving", F.round(1 - F.col("after") / F.col("before"), 6))


@R.query(f"{P()}, c AS (SELECT model, params_b, {M.cells_sql()} FROM attempt_log GROUP BY ALL) SELECT model, params_b, round(params_b / 7, 6) AS times_student, round(2.0::DOUBLE * tp / (2 * tp + fp + fn), 6) AS f1, round(2.0::DOUBLE * tp / (2 * tp + fp + fn) / params_b, 6) AS f1_per_b, 'simulated' AS responder FROM c")
def size_efficiency(spark, sf):
    p = M.f1_by(preds(spark, sf), ("params_b",))
    return p.select("model", "params_b", F.round(F.col("params_b") / 7, 6).alias("times_student"), F.round("f1", 6).alias("f1"), F.round(F.col("f1") / F.col("params_b"), 6).alias("f1_per_b"), F.lit("simulated").alias("responder"))


_OK = f"verdict = {TRUE}"


@R.query(f"""{S}, {G.attempts_sql()}, st AS (SELECT 0 AS place, 'asked' AS stage, count(*) AS rows, count(DISTINCT sample_id) AS samples FROM attempt_log UNION ALL SELECT 1, 'within length', count(*), count(DISTINCT sample_id) FROM attempt_log WHERE total_tokens <= 32000
UNION ALL SELECT 2, 'right', count(*), count(DISTINCT sample_id) FROM attempt_log WHERE total_tokens <= 32000 AND {_OK} UNION ALL SELECT 3, 'kept', count(DISTINCT (sample_id, model)), count(DISTINCT sample_id) FROM attempt_log WHERE total_tokens <= 32000 AND {_OK}) SELECT * FROM st""")
def funnel(spark, sf):
    a = G.respond(base(spark, sf))
    short = G.length_filter(a)
    return M.funnel({"asked": a, "within length": short, "right": G.right(short), "kept": G.reject(a)})


@R.query(f"{P(('student-final',))} SELECT verdict, count(*) AS n, rank() OVER (ORDER BY count(*) DESC)::INT AS rank FROM attempt_log WHERE NOT is_vuln AND verdict <> 'benign' GROUP BY verdict")
def false_positive_classes(spark, sf):
    from pyspark.sql.window import Window

    wrong = preds(spark, sf, ("student-final",)).where("NOT is_vuln AND verdict <> 'benign'").groupBy("verdict").agg(F.count("*").alias("n"))
    return wrong.withColumn("rank", F.rank().over(Window.orderBy(F.desc("n"))))


@R.query(f"{P(ALL)} SELECT sample_id, count(*) FILTER (verdict = 'benign') AS say_benign FROM attempt_log WHERE is_vuln GROUP BY sample_id HAVING count(*) FILTER (verdict = 'benign') >= 5")
def noise_suspects(spark, sf):
    """Vulnerable samples that most models call benign: perhaps wrongly labelled."""
    return preds(spark, sf).where("is_vuln").groupBy("sample_id").agg(F.count_if(F.col("verdict") == "benign").alias("say_benign")).where("say_benign >= 5")


@R.query(f"{P(('T1', 'T2'))} SELECT a.is_vuln, coalesce(a.verdict, 'none') = 'benign' AS t1_benign, coalesce(b.verdict, 'none') = 'benign' AS t2_benign, count(*) AS n FROM attempt_log a JOIN attempt_log b USING (sample_id) WHERE a.model = 'T1' AND b.model = 'T2' GROUP BY ALL")
def teacher_bias(spark, sf):
    p = preds(spark, sf, ("T1", "T2"))
    said = lambda m: F.max(F.when(F.col("model") == m, F.coalesce(F.col("verdict") == "benign", F.lit(False))))
    return p.groupBy("sample_id", "is_vuln").agg(said("T1").alias("t1_benign"), said("T2").alias("t2_benign")).groupBy("is_vuln", "t1_benign", "t2_benign").agg(F.count("*").alias("n"))


@R.query()
def bootstrap_f1(spark, sf):
    return M.bootstrap(preds(spark, sf, ("student-final", "T1", "T2")))


# ---- baselines

_RULES = f"""tr AS (SELECT DISTINCT sample_id, is_vuln, cls, unnest({TOKENS_SQL.format('code')}) AS word FROM sample WHERE split = 'train' AND is_vuln IS NOT NULL),
rp AS (SELECT word, count(*) FILTER (is_vuln) AS support FROM tr GROUP BY word HAVING count(*) FILTER (NOT is_vuln) = 0),
rc AS (SELECT word, cls AS rule_cls FROM (SELECT word, cls, count(*) AS c FROM tr WHERE is_vuln GROUP BY ALL) QUALIFY row_number() OVER (PARTITION BY word ORDER BY c DESC, cls) = 1),
rules AS (SELECT word, support, rule_cls FROM rp JOIN rc USING (word) WHERE support >= {{}}),
te AS (SELECT DISTINCT sample_id, unnest({TOKENS_SQL.format('code')}) AS word FROM sample WHERE split = 'test' AND is_vuln IS NOT NULL),
hit AS (SELECT sample_id, rule_cls, word FROM te JOIN rules USING (word) QUALIFY row_number() OVER (PARTITION BY sample_id ORDER BY support DESC, word) = 1)"""
_SCAN = "SELECT s.sample_id, CASE WHEN h.sample_id IS NULL THEN 'benign' ELSE 'CWE-' || rule_cls END AS verdict, h.word FROM sample s LEFT JOIN hit h USING (sample_id) WHERE split = 'test' AND is_vuln IS NOT NULL"


def rules(spark, sf, support):
    return B.learn_rules(base(spark, sf).where("split = 'train'"), support=support)


def _scan_query(name, support):
    @R.query(f"{S}, {_RULES.format(support)} {_SCAN}", name=name)
    def run(spark, sf):
        return B.rule_scan(base(spark, sf).where(TEST), rules(spark, sf, support)).select("sample_id", "verdict", "word")


_scan_query("rule_scan", 3)
_scan_query("rule_scan_ext", 2)

_STRUCT = r"1000 * length(regexp_replace(code, '[^!#$%&*]', '', 'g')) >= 20 * greatest(length(code), 1)", r"length(regexp_replace(code, '[^(\[{]', '', 'g')) <> length(regexp_replace(code, '[^)\]}]', '', 'g'))"


@R.query(f"""{S}, st AS (SELECT sample_id, cls, is_vuln, split, CASE WHEN {_STRUCT[0]} THEN 1 ELSE 0 END + CASE WHEN {_STRUCT[1]} THEN 2 ELSE 0 END AS form FROM sample WHERE is_vuln IS NOT NULL),
sr AS (SELECT form, cls AS rule_cls FROM (SELECT form, cls, count(*) AS c FROM st WHERE split = 'train' AND is_vuln AND form > 0 GROUP BY ALL) QUALIFY row_number() OVER (PARTITION BY form ORDER BY c DESC, cls) = 1)
SELECT sample_id, CASE WHEN rule_cls IS NULL THEN 'benign' ELSE 'CWE-' || rule_cls END AS verdict FROM st LEFT JOIN sr USING (form) WHERE split = 'test'""")
def rule_scan_b(spark, sf):
    """The form rules name the class that vulnerable training rows of the form have most; test classes are never read."""
    s = base(spark, sf)
    return B.structure_scan(s.where(TEST), B.learn_structure(s.where("split = 'train'"))).select("sample_id", "verdict")


@R.query(f"{S}, {_RULES.format(3)} SELECT s.sample_id, h.sample_id IS NOT NULL AS flagged FROM sample s LEFT JOIN hit h USING (sample_id) WHERE split = 'test' AND is_vuln IS NOT NULL")
def guard_scan(spark, sf):
    return B.guard_scan(base(spark, sf).where(TEST), rules(spark, sf, 3))


_SRC, _SINK = "[0-9]|the", "and|der"


@R.query(f"{S}, l AS (SELECT sample_id, string_split(code, chr(10)) AS ls FROM sample), e AS (SELECT sample_id, unnest(ls) AS x, unnest(range(0, len(ls))) AS i FROM l), b AS (SELECT sample_id, count(*) AS lines, min(i) FILTER (regexp_matches(x, '{_SRC}')) AS f, max(i) FILTER (regexp_matches(x, '{_SINK}')) AS z FROM e GROUP BY sample_id) SELECT sample_id, lines::INT AS lines, count(*) FILTER (i BETWEEN f AND z)::INT AS kept, md5(coalesce(string_agg(x, chr(10) ORDER BY i) FILTER (i BETWEEN f AND z), '')) AS slice_md5 FROM b JOIN e USING (sample_id) GROUP BY sample_id, lines")
def taint_slice(spark, sf):
    return B.slice_context(samples(spark, sf), _SRC, _SINK).select("sample_id", "lines", "kept", F.md5("slice").alias("slice_md5"))


def neighbours(spark, sf, k):
    e = load(spark, sf, "embeddings")
    return I.knn(e.where("vec_id % 20 = 0"), e, k)


_KNN = """u AS (SELECT vec_id, label, embedding::DOUBLE[] AS v FROM embeddings), n AS (SELECT *, sqrt(list_sum(list_transform(v, lambda x: x * x))) AS z FROM u),
p AS (SELECT q.vec_id AS q, b.vec_id AS b, b.label, round(list_dot_product(q.v, b.v) / (q.z * b.z), 9) AS s FROM n q JOIN n b ON q.vec_id <> b.vec_id WHERE q.vec_id % 20 = 0),
k AS (SELECT q, b, label, row_number() OVER (PARTITION BY q ORDER BY s DESC, b) AS rank FROM p QUALIFY rank <= 16)"""


@R.query(f"WITH {_KNN}, v AS (SELECT q, label, count(*) AS c FROM k WHERE rank <= 8 GROUP BY ALL) SELECT q AS vec_id, label AS voted FROM v QUALIFY row_number() OVER (PARTITION BY q ORDER BY c DESC, label) = 1")
def rag_knn(spark, sf):
    """Retrieval: the label most of the eight nearest vectors have."""
    near = neighbours(spark, sf, 8).groupBy("q", "label").agg(F.count("*").alias("c"))
    return near.groupBy(F.col("q").alias("vec_id")).agg(F.min(F.struct((-F.col("c")).alias("c"), "label")).alias("m")).select("vec_id", F.col("m.label").alias("voted"))


@R.query(f"WITH {_KNN}, ks(k) AS (VALUES (1), (4), (8), (16)), v AS (SELECT q, ks.k AS kk, label, count(*) AS c FROM k, ks WHERE rank <= ks.k GROUP BY ALL), w AS (SELECT q, kk, label FROM v QUALIFY row_number() OVER (PARTITION BY q, kk ORDER BY c DESC, label) = 1) SELECT kk AS k, count(*) AS queries, count(*) FILTER (w.label = e.label) AS hits FROM w JOIN embeddings e ON vec_id = q GROUP BY kk")
def vote_curve_knn(spark, sf):
    """Neighbours as parallel answers: accuracy of the vote of 1, 4, 8 and 16."""
    log = neighbours(spark, sf, 16).select(F.col("q").alias("sample_id"), F.col("rank").alias("attempt"), "label")
    aggs = {k: F.sum((F.col("attempt") <= k).cast("int")) for k in (1, 4, 8, 16)}
    per = log.groupBy("sample_id", "label").agg(*[a.alias(f"v{k}") for k, a in aggs.items()])
    best = per.groupBy("sample_id").agg(*[F.min(F.struct((-F.col(f"v{k}")).alias("v"), "label")).alias(f"b{k}") for k in aggs])
    flat = best.select("sample_id", F.inline(F.array(*[F.struct(F.lit(k).alias("k"), F.col(f"b{k}.label").alias("answer")) for k in aggs])))
    truth = load(spark, sf, "embeddings").select(F.col("vec_id").alias("sample_id"), "label")
    return flat.join(truth, "sample_id").groupBy("k").agg(F.count("*").alias("queries"), F.count_if(F.col("answer") == F.col("label")).alias("hits"))


@R.query(rate_sql("model", ("base", "T1", "T2", "P1", "P2", "student-final")))
def compare_models(spark, sf):
    return rate_df(preds(spark, sf, ("base", "T1", "T2", "P1", "P2", "student-final")), ())


def _ablation(name, models, by=()):
    @R.query(rate_sql(", ".join(("model", *by)), models), name=name)
    def run(spark, sf):
        return rate_df(preds(spark, sf, models), by)


_ablation("w8_reasoning", ("student-final", "student-no-reason"))
_ablation("w8_reasoning_ood", ("student-final", "student-no-reason"), ("ood_cwe",))
_ablation("w9_two_teachers", ("student-raw", "student-raw-T1", "student-raw-T2"))
_ablation("w10_filter_and_hints", ("student-raw", "student-filtered"))
_ablation("w11_condensed", ("student-filtered", "student-final"))


@R.query()
def w3_measured(spark, sf):
    """F1 by language of what is measured, not simulated: rules, structure and two students trained on train rows."""
    s = base(spark, sf)
    train, test = s.where("split = 'train'"), s.where(TEST).cache()
    out = B.rule_scan(test, B.learn_rules(train, support=3), "rules").select("sample_id", "model", "verdict")
    out = out.union(B.rule_scan(test, B.learn_rules(train, support=2), "rules, extended").select("sample_id", "model", "verdict"))
    out = out.union(B.structure_scan(test, B.learn_structure(train)).select("sample_id", "model", "verdict"))
    for kind in ("bayes", "logistic"):
        out = out.union(B.student_predict(B.fit_student(train, kind=kind), test, f"student, {kind}"))
    return rate_df(out.join(test.select("sample_id", "lang", "is_vuln", "cls"), "sample_id"), ("lang",), kind="measured")


@R.query()
def slice_student(spark, sf):
    """The slicing baseline: a student that sees slices only, against one that sees all."""
    s = base(spark, sf)
    cut = s.join(B.slice_context(s, _SRC, _SINK).select("sample_id", "slice"), "sample_id").withColumn("code", F.col("slice")).drop("slice")
    out = None
    for name, d in (("whole", s), ("slice", cut)):
        p = B.student_predict(B.fit_student(d.where("split = 'train'")), d.where(TEST), name)
        out = p if out is None else out.union(p)
    return rate_df(out.join(s.select("sample_id", "is_vuln", "cls"), "sample_id"), (), kind="measured")
