"""Chat formatting: speakers of a plain transcript by a hidden Markov model, then one canonical form.

A hidden state is a role and whether the line opens a turn. A line is seen as two
symbols, its speaker marker and its shape (length, how it ends, what it starts
with). Who a marker stands for is read off the whole transcript: names that come again
in the way most markers are written are its speakers, known names or not, and a
known name beside the one that its role goes by is a word of the text. The model is counted on transcripts whose roles are known. Viterbi's path over a
transcript's lines gives roles; a marker line's marker is cut off the text.
"""

from __future__ import annotations

import re
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ROLES = ("system", "user", "assistant")

#: Names of speakers, by role.
NAMES = {"system": ("system", "sys", "instructions", "context"), "user": ("user", "human", "customer", "question", "q", "prompter", "me", "usr"), "assistant": ("assistant", "bot", "ai", "agent", "answer", "a", "model", "gpt")}
#: Of these, such as are words of ordinary text too.
WORDS = ("instructions", "context", "customer", "question", "q", "me", "agent", "answer", "a", "model")
_BY_NAME = {n: k for k, r in enumerate(ROLES) for n in NAMES[r]}
#: Ways to mark a speaker at the start of a line; {} is the name.
MARKERS = (r"<(\w+)>", r"<\|(?:im_start\|>)?\s*(\w+)\s*(?:\|>)?", r"\[(?:/)?(\w+)\]:?", r"#{1,4}\s*(\w+)\s*:?(?=\s*$|\s*\n|:)", r"\*\*(\w+)\s*:?\*\*:?", r"(\w+)\s*:", r"(\w+)\s*>+")
_MARKER = re.compile(r"^[ \t]*(?:" + "|".join(f"(?:{m})" for m in MARKERS) + r")[ \t]*")
#: Marker symbols: 0 none, role + 1, then these.
OTHER, BESIDE, FIRST, SECOND = 4, 5, 6, 7
N_MARKS, N_SHAPES = 8, 36
STATES = [(r, o) for r in range(len(ROLES)) for o in (0, 1)]  # o: 0 opens a turn, 1 goes on


def marker(line: str) -> tuple[int, str, int] | None:
    """(way it is written, name in lower case, length), or None."""
    m = _MARKER.match(line[:200])
    if not m:
        return None
    way = next(k for k, g in enumerate(m.groups()) if g is not None)
    name = m.groups()[way].lower()
    if name not in _BY_NAME and (len(name) > 12 or line[m.end() :].startswith("//")):
        return None
    return way, name, m.end()


def speakers(marks: list[tuple[int, str, int] | None]) -> dict[tuple[int, str], int]:
    """Symbol of each (way, name) of a transcript. The way is that of most markers (then the first). There, of the
    known names of a role only those as frequent as the most frequent one stand for it, if that one comes again. Where
    user and assistant have such names, ordinary words that come once stand for nobody, but for the first marker of all.
    Unknown names that come again are speakers where user or assistant goes by no known name: the role left, or the first and the second of them."""
    times, ways = Counter((w, n) for w, n, _ in filter(None, marks)), Counter(w for w, _, _ in filter(None, marks))
    if not ways:
        return {}
    main = ways.most_common(1)[0][0]
    tops = [max((c for (w, n), c in times.items() if w == main and _BY_NAME.get(n) == r), default=0) for r in range(len(ROLES))]
    out, settled = {}, min(tops[1:]) > 1
    for k, (way, name) in enumerate(times):
        role = _BY_NAME.get(name)
        top = 0 if role is None else tops[role]
        own = role is not None and (not (settled and k and name in WORDS) if top < 2 else way == main and times[way, name] == top)
        out[way, name] = OTHER if role is None else role + 1 if own else BESIDE
    left = [r for r in (1, 2) if not any(w == main and s == r + 1 for (w, _), s in out.items())]
    new = [x for x, c in times.items() if x[0] == main and out[x] == OTHER and c > 1]
    if len(left) == 1 and len(new) == 1:
        out[new[0]] = (FIRST, SECOND)[left[0] - 1]
    elif len(left) == 2 and len(new) > 1:
        out[new[0]], out[new[1]] = FIRST, SECOND
    return out


def shape(text: str) -> int:
    t = text.strip()
    size = 0 if not t else 1 if len(t) < 80 else 2 if len(t) < 300 else 3
    end = 0 if t[-1:] == "?" else 1 if t[-1:] in {".", "!", ":"} else 2
    start = 0 if re.match(r"(?:[-*]|\d+[.)])\s", t) else 1 if t[:1].isupper() else 2
    return (size * 3 + end) * 3 + start


def observe(text: str) -> tuple[list[str], np.ndarray, np.ndarray, list[int]]:
    """Lines, their marker and shape symbols, and the lengths of the markers."""
    lines = text.split("\n")
    marks = [marker(x) for x in lines]
    who = speakers(marks)
    seen = [who[m[:2]] if m else 0 for m in marks]
    cuts = [m[2] if m and s not in (OTHER, BESIDE) else 0 for m, s in zip(marks, seen, strict=True)]
    return lines, np.array(seen), np.array([shape(x[c:]) for x, c in zip(lines, cuts, strict=True)]), cuts


@dataclass
class Model:
    """Logarithms: start[state], step[state, state], mark[state, symbol], look[state, symbol]."""

    start: np.ndarray
    step: np.ndarray
    mark: np.ndarray
    look: np.ndarray

    def viterbi(self, marks: np.ndarray, shapes: np.ndarray) -> np.ndarray:
        seen = self.mark[:, marks].T + self.look[:, shapes].T
        best, back = self.start + seen[0], np.zeros(seen.shape, np.int8)
        for t in range(1, len(seen)):
            paths = best[:, None] + self.step
            back[t] = paths.argmax(0)
            best = paths[back[t], np.arange(len(best))] + seen[t]
        out = np.zeros(len(seen), np.int64)
        out[-1] = best.argmax()
        for t in range(len(seen) - 1, 0, -1):
            out[t - 1] = back[t, out[t]]
        return out


def from_counts(start, step, mark, look, prior: float = 0.1) -> Model:
    """With priors: a line can't go on in another role than the one before, and names open turns."""
    ok = np.array([[b[1] == 0 or a[0] == b[0] for b in STATES] for a in STATES])
    first = np.array([o == 0 for _, o in STATES])
    own = lambda r: {r + 1, (0, FIRST, SECOND)[r]} - {0}
    named = np.array([[20 if m in ({0} if o else own(r)) else 2 if m in ({OTHER, BESIDE} if o else {0}) else 0.1 for m in range(N_MARKS)] for r, o in STATES])  # a turn opens with its role's name
    normal = lambda x: np.log(x / x.sum(-1, keepdims=True))


    def blend(seen: np.ndarray, common: np.ndarray, trust: float = 0.9) -> np.ndarray:
        """Shares seen in a state, mixed with common ones, so that what no state has shown speaks for none, however few lines a state has."""
        n, common = seen.sum(1, keepdims=True), common / common.sum(1, keepdims=True)
        return np.log(np.where(n > 0, trust * seen / np.maximum(n, 1) + (1 - trust) * common, common))

    return Model(np.log((start + prior) / (start + prior).sum()) + np.where(first, 0, -20.0), normal(np.where(ok, step + 5.0, 1e-9)), blend(mark, named), blend(look, look.sum(0, keepdims=True) + np.ones_like(look)))


def count(texts: list[str], roles: list[list[tuple[int, int]]]) -> np.ndarray:
    """Counts, in one row: roles holds (role, opens) for every line."""
    n = len(STATES)
    start, step, mark, look = np.zeros(n), np.zeros((n, n)), np.zeros((n, N_MARKS)), np.zeros((n, N_SHAPES))
    for text, own in zip(texts, roles, strict=True):
        _, m, s, _ = observe(text)
        state = np.array([STATES.index(x) for x in own])
        start[state[0]] += 1
        np.add.at(step, (state[:-1], state[1:]), 1)
        np.add.at(mark, (state, m), 1)
        np.add.at(look, (state, s), 1)
    return np.concatenate([start, step.ravel(), mark.ravel(), look.ravel()])


def _split(row: np.ndarray) -> tuple[np.ndarray, ...]:
    n = len(STATES)
    at = np.cumsum([n, n * n, n * N_MARKS])
    start, step, mark, look = np.split(row, at)
    return start, step.reshape(n, n), mark.reshape(n, N_MARKS), look.reshape(n, N_SHAPES)


def fit(transcripts: DataFrame) -> Model:
    """Counts over all transcripts: columns transcript, roles (array of 2 * role + goes on, one a line). One row a task reaches the driver's sum."""

    def run(batches):
        for batch in batches:
            texts, roles = (batch.column(c).to_pylist() for c in ("transcript", "roles"))
            keep = [k for k, t in enumerate(texts) if t is not None and roles[k]]
            row = count([texts[k] for k in keep], [[divmod(x, 2) for x in roles[k]] for k in keep])
            at = np.flatnonzero(row)
            yield pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), pa.array(row[at].astype(np.int64))], ["at", "n"])

    n = len(STATES)
    row = np.zeros(n + n * n + n * N_MARKS + n * N_SHAPES)
    for r in transcripts.select("transcript", "roles").mapInArrow(run, "at int, n long").groupBy("at").agg(F.sum("n").alias("n")).collect():
        row[r["at"]] = r.n
    return from_counts(*_split(row))


def turns_of(text: str, model: Model) -> list[tuple[int, str]]:
    """(role, text) of the turns of one transcript; a turn without words is dropped."""
    if not text.strip():
        return []
    lines, marks, shapes, cuts = observe(text)
    out: list[tuple[int, list[str]]] = []
    for line, cut, state in zip(lines, cuts, model.viterbi(marks, shapes), strict=True):
        role, goes_on = STATES[state]
        if not goes_on or not out:
            out.append((role, [line[cut:]]))
        else:
            out[-1][1].append(line)
    done = [(r, "\n".join(x).replace("<|im_end|>", "").replace("<|end|>", "").strip()) for r, x in out]
    return [(r, t) for r, t in done if t]


def render(turns: list[tuple[int, str]]) -> str:
    """Canonical form: <|role|> on a line of its own, the text, <|end|>."""
    return "".join(f"<|{ROLES[r]}|>\n{t}\n<|end|>\n" for r, t in turns)


def parse(transcripts: DataFrame, model: Model) -> DataFrame:
    """conv_id, part, n_turns, roles (array), turns (array of text), chat (canonical). columns in: conv_id, transcript and, where there is one, part; one row each.

    Null or blank transcripts have no turns and an empty chat. Null conv_id stays null.
    Repeated rows are parsed each. An empty table gives no rows.
    """
    keys = [c for c in ("conv_id", "part") if c in transcripts.columns]
    rows = transcripts.select(*keys, F.col("transcript").cast("string").alias("transcript"))

    def run(batches):
        for batch in batches:
            done = [turns_of(t or "", model) for t in batch.column("transcript").to_pylist()]
            yield pa.RecordBatch.from_arrays([
                *[batch.column(c) for c in keys], pa.array([len(d) for d in done], pa.int64()), pa.array([[ROLES[r] for r, _ in d] for d in done], pa.list_(pa.string())),
                pa.array([[t for _, t in d] for d in done], pa.list_(pa.string())), pa.array([render(d) for d in done], pa.string())], [*keys, "n_turns", "roles", "turns", "chat"])

    types = dict(rows.dtypes)
    return rows.mapInArrow(run, "".join(f"{c} {types[c]}, " for c in keys) + "n_turns long, roles array<string>, turns array<string>, chat string")


#: Styles that transcripts of a table of turns are written in: name of each role, and how it stands before the text.
STYLES = (("System: {}", "User: {}", "Assistant: {}"), ("### System\n{}", "### Human\n{}", "### Assistant\n{}"), ("[SYSTEM] {}", "[USER] {}", "[BOT] {}"), ("<|system|>\n{}", "<|user|>\n{}", "<|assistant|>\n{}"), ("Context: {}", "Q: {}", "A: {}"), ("**System:** {}", "**Me:** {}", "**AI:** {}"))


def transcripts_of(turns: DataFrame, *, run: int = 1000) -> DataFrame:
    """Plain transcripts of a table of turns (conv_id, turn, role, text): conv_id, part, transcript, roles.

    The style goes by conv_id. Turns ``run`` numbers apart are in different parts, which bounds what one row
    gathers; rows without conv_id or turn are parts of their own. Null text is empty; other roles count as user.
    """
    own = F.xxhash64("conv_id", "turn", "role", "text")
    part = F.when(F.col("conv_id").isNull() | F.col("turn").isNull(), own).otherwise(F.expr(f"turn div {run}"))
    role = F.when(F.lower("role") == "system", 0).when(F.lower("role") == "assistant", 2).otherwise(1)
    style = F.pmod(F.coalesce(F.xxhash64("conv_id"), F.lit(0)), F.lit(len(STYLES)))
    form: Column = F.lit(STYLES[0][1])
    for s, names in enumerate(STYLES):
        for r, name in enumerate(names):
            form = F.when((style == s) & (role == r), F.lit(name)).otherwise(form)
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    line = F.concat(F.split_part(form, F.lit("{}"), F.lit(1)), text)
    n_lines = F.size(F.split(line, "\n", -1))
    flags = F.concat(F.array((role * 2).cast("int")), F.array_repeat((role * 2 + 1).cast("int"), n_lines - 1))
    rows = turns.select("conv_id", part.alias("part"), F.struct(F.col("turn").alias("turn"), line.alias("line"), flags.alias("flags")).alias("t"))
    got = rows.groupBy("conv_id", "part").agg(F.array_sort(F.collect_list("t")).alias("t"))
    return got.select("conv_id", "part", F.array_join("t.line", "\n").alias("transcript"), F.flatten("t.flags").alias("roles"))
