"""A stand-in for model answers, by whole-number arithmetic that Spark and DuckDB agree on.

Numbers obtained with it test the computations on answers; the order of models is
put in by the table below and is no finding.
"""

from __future__ import annotations

from dataclasses import dataclass

M = 2147483647
#: Shares in a thousand.
HARD, HINTED, MALFORMED, CLASSES = 300, 90, 20, 20


@dataclass(frozen=True)
class Profile:
    no: int
    params_b: int
    right: int
    fn_bias: int
    mean_tokens: int
    ms_per_token: int


#: Free parameters, not measurements.
MODELS = {
    "T1": Profile(1, 600, 620, 700, 20300, 6), "T2": Profile(2, 32, 560, 300, 20300, 3), "base": Profile(3, 7, 350, 500, 200, 1),
    "P1": Profile(4, 210, 640, 400, 1500, 5), "P2": Profile(5, 210, 630, 200, 283, 5), "student-raw": Profile(6, 7, 600, 500, 8000, 1),
    "student-raw-T1": Profile(7, 7, 560, 700, 8000, 1), "student-raw-T2": Profile(8, 7, 540, 300, 8000, 1), "student-filtered": Profile(9, 7, 680, 500, 1810, 1),
    "student-final": Profile(10, 7, 720, 500, 362, 1), "student-no-reason": Profile(11, 7, 520, 500, 5, 1),
}
TEACHERS = ("T1", "T2")


def draw(s: str, t: str, a: str, z: int, sql: bool = False) -> str:
    """The draw h(s, t, a, z) as an expression; sql: DuckDB's division."""
    div = "//" if sql else "div"
    x = f"(cast({s} as bigint) * 48271 + cast({t} as bigint) * 16807 + cast({a} as bigint) * 69621 + {z} * 40692 + 12345) % {M}"
    x = f"((({x}) % 46341) * (({x}) {div} 46341 + 17) + ({x})) % {M}"
    return f"((({x}) % 46337) * (({x}) {div} 46337 + 29) + ({x})) % {M}"


def model_values(names) -> str:
    """SQL rows of the chosen models."""
    rows = ", ".join(f"('{m}', {p.no}, {p.params_b}, {p.right}, {p.fn_bias}, {p.mean_tokens}, {p.ms_per_token}, {str(m in TEACHERS).lower()})" for m, p in MODELS.items() if m in names)
    return f"(VALUES {rows}) AS m(model, t, params_b, p_right, fn_bias, mean_tokens, ms, teacher)"


def answer_columns(sql: bool = False, hinted: bool = False) -> dict[str, str]:
    """Expressions of an attempt, in an order in which each may use those before. Inputs: sample_id, cls, is_vuln, n_tokens, attempt (from 1) and the model's columns."""
    div = "//" if sql else "div"
    d = lambda z: draw("sample_id", "t", "(attempt - 1)", z, sql)
    hard = draw("sample_id", "0", "0", 1, sql)
    right = f"({d(3)}) % 1000 < {HINTED}" if hinted else f"({hard}) % 1000 >= {HARD} AND ({d(0)}) % 1000 < p_right"
    text = "varchar" if sql else "string"
    return {
        "is_right": right,
        "out_tokens": f"CAST(CASE WHEN teacher THEN 300 + ({d(2)}) % 40000 ELSE mean_tokens {div} 2 + ({d(2)}) % mean_tokens END AS INT)",
        "well_formed": f"({d(5)}) % 1000 >= {MALFORMED}",
        "claim": f"CAST(CASE WHEN is_right THEN CASE WHEN is_vuln THEN cls ELSE -1 END WHEN is_vuln THEN CASE WHEN ({d(6)}) % 1000 < fn_bias THEN -1 ELSE (cls + 1) % {CLASSES} END ELSE ({d(4)}) % {CLASSES} END AS INT)",
        "second": f"CAST(({d(7)}) % {CLASSES} AS INT)",
        "verdict": f"CASE WHEN NOT well_formed THEN NULL WHEN claim < 0 THEN 'benign' ELSE 'CWE-' || CAST(claim AS {text}) END",
        "runtime_ms": "CAST(out_tokens AS BIGINT) * ms",
        "total_tokens": "n_tokens + out_tokens",
    }
