"""Personal data: fixed patterns, and a skip-chain conditional random field that adds what they miss.

Tokens that hold a digit or an at sign are nodes. Neighbours on the line of tokens
share a potential, and so does each token with the next one in the document that
has the same digits or letters, however far off (the skip edges). Potentials are
fitted piece by piece: a logistic regression for the token's own features, and the
log ratio of joint to single label shares for both kinds of edges. All three need
counts only, of a fixed number of feature combinations, gathered over every
document. What the fixed patterns find is observed, and tokens
that they miss though they find a similar one are left out of the counts; loopy belief propagation then
carries labels along the edges, so that a number written once in full and once in
part gets one label.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_left
from itertools import accumulate
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from detectlab.llm.wordhash import pieces

KINDS = ("email", "ip", "card", "phone")  # fixed values, in order
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
_CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_DIGITS = re.compile("[0-9]+")
_TOKEN = re.compile(r"[^\x20\x09-\x0D]+")
_ACTIVE = re.compile(r"[0-9@]")
_SPACE = re.compile(r"[\x20\x09-\x0D]")
_BLANKS = " \t\n\r\x0b\x0c"  # the same characters


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = int(c)
        total += d if k % 2 == 0 else (2 * d - 9 if d > 4 else 2 * d)
    return total % 10 == 0


def _emails(text: str):
    """Local parts are read back from each at sign, no further than the match before: one pass over any text."""
    end, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > end and text[start - 1] in _LOCAL:
            start -= 1
        found = _DOMAIN.match(text, at + 1) if start < at else None
        if found:
            yield start, found.end()
            end = found.end()
        else:
            end = max(end, at + 1) if start == at else end
        at = text.find("@", max(end, at + 1))


def _ips(text: str):
    for m in _IP.finditer(text):
        if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m[0].split(".")):
            yield m.span()


def _cards(text: str):
    for m in _CARD.finditer(text):
        digits = m[0].replace(" ", "").replace("-", "")
        if 12 <= len(digits) <= 19 and luhn(digits):
            yield m.span()


def _phones(text: str):
    for m in _PHONE.finditer(text):
        if 9 <= sum(map(len, _DIGITS.findall(m[0]))) <= 15:
            yield m.span()


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of the fixed patterns, by start then kind."""
    out = []
    if "@" in text:
        out += [(s, 0, e) for s, e in _emails(text)]
    if _ACTIVE.search(text):
        out += [(s, 1, e) for s, e in _ips(text)] + [(s, 2, e) for s, e in _cards(text)]
        if "+" in text:
            out += [(s, 3, e) for s, e in _phones(text)]
    return sorted(out)


def encode(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in spans)


def redact(text: str, spans: list[tuple[int, int, int]], mark: str = "[{}]") -> str:
    """text with each span (overlapping ones merged) replaced by its kind."""
    out, at = [], 0
    for s, k, e in sorted(spans):
        if s >= at:
            out += [text[at:s], mark.format(KINDS[k])]
        at = max(at, e)
    return "".join(out) + text[at:]


# ---- tokens and features

#: Sizes of the features of a token; their product bounds the table of counts.
SHAPES = (2, 9, 4, 2, 2, 3, 2, 3)
_CLASS = np.array([0, 1, 1, 1, 2, 2, 2, 2, 3, 4, 4, 4, 5, 5, 5, 5, 6, 7, 7, 7, 8])


def _features(token: str, before: str) -> int:
    digits = sum(map(len, _DIGITS.findall(token)))
    letters = any(c.isalpha() for c in token)
    hexed = letters and digits >= 4 and re.fullmatch(r"[\W_]*[0-9a-fA-F]+[\W_]*", token) is not None
    tail = before[-1:] if before else ""
    values = ("@" in token, int(_CLASS[min(digits, 20)]), min(token.count("."), 3), token[:1] == "+", token[:1] == "(" or token[-1:] == ")", 2 if hexed else int(letters), "-" in token[1:], 1 if tail in ":=" and tail else 2 if _DIGITS.search(before) else 0)
    code = 0
    for v, n in zip(values, SHAPES, strict=True):
        code = code * n + int(v)
    return code


def _key(token: str) -> str:
    """What similar tokens share: the last nine of seven digits or more, else letters and digits in lower case."""
    digits = "".join(_DIGITS.findall(token))
    return digits[-9:] if len(digits) >= 7 and "@" not in token else re.sub(r"[\W_]+", "", token.lower())


@dataclass
class Graph:
    """Nodes of several texts. span: start and end. label: 0 none, else the kind + 1 of a fixed pattern. group: the
    first node of the text with the same key. edges: near, far."""

    text: list[int]
    span: list[tuple[int, int]]
    code: list[int]
    label: list[int]
    group: list[int]
    near: list[tuple[int, int]]
    far: list[tuple[int, int]]


def active_tokens(text: str):
    """(start, end) of the tokens with a digit or an at sign; every character is looked at a fixed number of times."""
    end = 0
    while m := _ACTIVE.search(text, end):
        at = m.start()
        start = 1 + max(end - 1, *(text.rfind(c, end, at) for c in _BLANKS))
        stop = _SPACE.search(text, at)
        end = stop.start() if stop else len(text)
        yield start, end


def graph_of(texts: list[str | None], bases: list[list[tuple[int, int, int]]]) -> Graph:
    g = Graph([], [], [], [], [], [], [])
    for t, (text, spans) in enumerate(zip(texts, bases, strict=True)):
        if not text or not _ACTIVE.search(text):
            continue
        last: dict[str, int] = {}
        at, end_before = 0, -2
        for start, end in active_tokens(text):
            n, token = len(g.text), text[start:end]
            gap = text[max(0, start - 24) : start].rstrip(_BLANKS)
            before = (_TOKEN.findall(gap) or [""])[-1]
            while at < len(spans) and spans[at][2] <= start:
                at += 1
            label = next((k + 1 for s, k, e in spans[at : at + 8] if s < end and e > start), 0)
            g.text.append(t)
            g.span.append((start, end))
            g.code.append(_features(token, before))
            g.label.append(label)
            if end_before >= 0 and not text[end_before:start].strip(_BLANKS):
                g.near.append((n - 1, n))
            end_before = end
            key = _key(token)
            g.group.append(n)
            if len(key) >= 4:
                if key in last:
                    g.far.append((last[key], n))
                    g.group[n] = g.group[last[key]]
                last[key] = n
    return g


@dataclass
class Field:
    """Log potentials: own[code, label], near and far[label, label]."""

    own: dict[int, np.ndarray]
    near: np.ndarray
    far: np.ndarray
    default: np.ndarray

    def infer(self, g: Graph, rounds: int = 30, damp: float = 0.3) -> np.ndarray:
        """Label shares of every node by loopy sum-product; labels of fixed patterns are observed. The messages of a
        text stop when none of its own moves, so that its labels don't depend on the texts beside it."""
        n, k = len(g.text), len(KINDS) + 1
        own = np.array([self.own.get(c, self.default) for c in g.code]).reshape(n, k)
        seen = np.array(g.label, np.int64)
        own[seen > 0] = -30.0
        own[np.flatnonzero(seen > 0), seen[seen > 0]] = 0.0
        edges = np.array(g.near + g.far, np.int64).reshape(-1, 2)
        if not len(edges):
            e = np.exp(own - own.max(1, keepdims=True))
            return e / e.sum(1, keepdims=True)
        pot = np.concatenate([np.repeat(self.near[None], len(g.near), 0), np.repeat(self.far[None], len(g.far), 0)])
        src, dst = np.concatenate([edges[:, 0], edges[:, 1]]), np.concatenate([edges[:, 1], edges[:, 0]])
        pot = np.concatenate([pot, pot.transpose(0, 2, 1)])
        back = np.concatenate([np.arange(len(edges)) + len(edges), np.arange(len(edges))])
        msg, of = np.zeros((len(src), k)), np.array(g.text, np.int64)[src]
        live = np.ones(len(src), bool)
        for _ in range(rounds):
            total = own.copy()
            np.add.at(total, dst, msg)
            out = (total[src] - msg[back])[:, :, None] + pot
            top = out.max(1)
            new = top + np.log(np.exp(out - top[:, None]).sum(1))
            new -= new.max(1, keepdims=True)
            new = damp * msg + (1 - damp) * new
            moved = np.zeros(of.max() + 1)
            np.maximum.at(moved, of, np.abs(new - msg).max(1))
            msg = np.where(live[:, None], new, msg)
            live &= moved[of] >= 1e-4
            if not live.any():
                break
        np.add.at(own, dst, msg)
        e = np.exp(own - own.max(1, keepdims=True))
        return e / e.sum(1, keepdims=True)


def fit(docs: DataFrame, *, steps: int = 400, ridge: float = 1e-3) -> Field:
    """Fits the field on counts over all texts with a digit or at sign; at most prod(SHAPES) * 5 + 50 rows come to the driver."""
    k = len(KINDS) + 1
    chosen = docs.where(F.col("text").rlike("[0-9@]")).select(F.col("text").cast("string").alias("text"))

    def run(batches):
        for batch in batches:
            for part in pieces(batch, "text", 16 << 20):
                texts = part.column("text").to_pylist()
                g = graph_of(texts, [base_spans(t) for t in texts])
                label, group = np.array(g.label, np.int64), np.array(g.group, np.int64)
                # a token the patterns pass over though they know another with its key: its label is missing, not none
                known = ~((label == 0) & np.isin(group, group[label > 0]))
                keys = [("own", (np.array(g.code, np.int64) * k + label)[known])]
                for name, edges in (("near", g.near), ("far", g.far)):
                    e = np.array(edges, np.int64).reshape(-1, 2)
                    e = e[known[e].all(1)]
                    keys.append((name, label[e[:, 0]] * k + label[e[:, 1]]))
                for name, values in keys:
                    v, c = np.unique(values, return_counts=True)
                    yield pa.RecordBatch.from_arrays([pa.array([name] * len(v), pa.string()), pa.array(v, pa.int64()), pa.array(c, pa.int64())], ["what", "key", "n"])

    rows = chosen.mapInArrow(run, "what string, key long, n long").groupBy("what", "key").agg(F.sum("n").alias("n")).collect()
    pair = {"near": np.full((k, k), 0.5), "far": np.full((k, k), 0.1) + 20 * np.eye(k)}  # prior: similar tokens agree
    counts: dict[int, np.ndarray] = {}
    for r in rows:
        if r.what == "own":
            counts.setdefault(r.key // k, np.zeros(k))[r.key % k] += r.n
        else:
            pair[r.what][r.key // k, r.key % k] += r.n
    pmi = {}
    for w, m in pair.items():
        m = (m + m.T) / 2
        share = m / m.sum()
        pmi[w] = np.clip(np.log(share / np.outer(share.sum(1), share.sum(0))), -3, 3)
    codes = sorted(counts)
    if not codes:
        none = np.log(np.array([0.96] + [0.01] * (k - 1)))
        return Field({}, pmi["near"], pmi["far"], none)
    x = np.stack([_one_hot(c) for c in codes])
    y = np.stack([counts[c] for c in codes])
    total = y.sum()
    w = np.zeros((x.shape[1], k))
    moment, square = np.zeros_like(w), np.zeros_like(w)
    for step in range(1, steps + 1):
        z = x @ w
        p = np.exp(z - z.max(1, keepdims=True))
        p /= p.sum(1, keepdims=True)
        grad = x.T @ (p * y.sum(1, keepdims=True) - y) / total + ridge * w
        moment, square = 0.9 * moment + 0.1 * grad, 0.999 * square + 0.001 * grad**2
        w -= 0.2 * (moment / (1 - 0.9**step)) / (np.sqrt(square / (1 - 0.999**step)) + 1e-8)
    z = x @ w
    z -= np.log(np.exp(z - z.max(1, keepdims=True)).sum(1, keepdims=True)) + z.max(1, keepdims=True)
    prior = np.log((y.sum(0) + 0.5) / (total + 0.5 * k))
    return Field(dict(zip(codes, z, strict=True)), pmi["near"], pmi["far"], prior)


def _one_hot(code: int) -> np.ndarray:
    out = [1.0]
    for n in reversed(SHAPES):
        out += [float(code % n == v) for v in range(n)]
        code //= n
    return np.array(out)


_EDGE = " \t\n\r\x0b\x0c.,;:!?\"'()[]{}<>|#*$%&="


def add_spans(texts: list[str | None], field: Field, sure: float = 0.9) -> tuple[list[list[tuple[int, int, int]]], list[list[tuple[int, int, int]]]]:
    """Spans of the fixed patterns, and these with what the field adds: nodes outside them with a label of share ``sure`` or more."""
    bases = [base_spans(t) if t else [] for t in texts]
    full = [list(b) for b in bases]
    g = graph_of(texts, bases)
    if g.text:
        share = field.infer(g)
        best = share[:, 1:].argmax(1)
        starts = [[a for a, _, _ in b] for b in bases]
        reach = [list(accumulate((b for _, _, b in x), max)) for x in bases]  # the furthest end so far
        for n in np.flatnonzero((share[:, 1:].max(1) >= sure) & (np.array(g.label) == 0)).tolist():
            t, (s, e) = g.text[n], g.span[n]
            text = texts[t]
            while s < e and text[s] in _EDGE:
                s += 1
            while e > s and text[e - 1] in _EDGE:
                e -= 1
            before = bisect_left(starts[t], e)
            if e > s and not (before and reach[t][before - 1] > s):
                full[t].append((s, int(best[n]), e))
    return bases, [sorted(x) for x in full]


def find(docs: DataFrame, field: Field | None = None, *, sure: float = 0.9) -> DataFrame:
    """doc_id, base (spans of the fixed patterns), spans (all): arrays of (start, kind, end), code points, end exclusive.

    One row per input row. Null text is empty and has none. Repeated rows are
    searched each. Long runs of one character cost time in proportion. An empty
    table gives no rows.
    """
    docs = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    field = field or fit(docs)
    span = pa.list_(pa.struct([("start", pa.int64()), ("kind", pa.string()), ("end", pa.int64())]))

    def run(batches):
        for batch in batches:
            for part in pieces(batch, "text", 16 << 20):
                bases, full = add_spans(part.column("text").to_pylist(), field, sure)
                named = [pa.array([[{"start": s, "kind": KINDS[k], "end": e} for s, k, e in x] for x in both], span) for both in (bases, full)]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), *named], ["doc_id", "base", "spans"])

    kind = "array<struct<start: long, kind: string, end: long>>"
    return docs.mapInArrow(run, f"doc_id {dict(docs.dtypes)['doc_id']}, base {kind}, spans {kind}")


def digest(found: DataFrame) -> DataFrame:
    """Counts by kind, hash of the fixed patterns' spans, and all spans, as strings kind:start:end."""
    text = lambda c: F.array_join(F.transform(c, lambda x: F.concat_ws(":", x.kind, x.start.cast("string"), x.end.cast("string"))), ",")

    def count(kind: str):
        return F.size(F.filter("base", lambda x: x.kind == kind)).cast("long").alias(f"n_{kind}")

    counts = [count(kind) for kind in KINDS]
    return found.select("doc_id", *counts, F.sha2(text("base"), 256).alias("base_sha256"), text("spans").alias("spans"))


def redact_documents(docs: DataFrame, field: Field | None = None, mark: str = "[{}]") -> DataFrame:
    """docs with every span replaced by its kind; columns unchanged."""
    field = field or fit(docs.select("doc_id", "text"))
    held = docs.select(F.struct("*").alias("doc"))

    def run(batches):
        for batch in batches:
            doc = batch.column(0)
            texts = pc.struct_field(doc, "text").to_pylist()
            _, full = add_spans(texts, field)
            clean = [t if t is None else redact(t, s, mark) for t, s in zip(texts, full, strict=True)]
            yield pa.RecordBatch.from_arrays([doc, pa.array(clean, pa.string())], ["doc", "clean"])

    out = held.mapInArrow(run, T.StructType([held.schema[0], T.StructField("clean", T.StringType())]))
    return out.select(*[F.col("clean").alias(c) if c == "text" else F.col(f"doc.`{c}`") for c in docs.columns])

