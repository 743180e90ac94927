"""Language identification in two steps: the family, then the language within it.

Texts are counts of hashed three-byte grams of lower-cased letters. A linear support
vector machine for each family, one against the rest, picks the family; within it, one
for each pair of languages votes. Weights are whole numbers, so scores don't depend
on how rows are grouped.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from detectlab.llm import wordhash as wh

GRAMS = 8192
SCALE = 1 << 16

#: Language code -> family. Other codes are families of their own.
FAMILIES = {
    "en": "germanic", "de": "germanic", "nl": "germanic", "sv": "germanic", "da": "germanic", "no": "germanic",
    "fr": "romance", "es": "romance", "it": "romance", "pt": "romance", "ro": "romance", "ca": "romance",
    "ru": "slavic", "uk": "slavic", "pl": "slavic", "cs": "slavic", "sk": "slavic", "bg": "slavic",
    "fi": "uralic", "et": "uralic", "hu": "uralic",
}


def held_out(doc_id: Column) -> Column:
    """Rows kept for testing: crc32 of the id as text leaves 2 modulo 4."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def _grams(texts) -> tuple[np.ndarray, np.ndarray]:
    """Gram numbers at every byte, and where each text's begin and end."""
    data, offsets = wh.buffer_of(texts)
    table = np.full(256, 32, np.uint8)
    for lo, hi in ((65, 91), (97, 123), (128, 256)):
        table[lo:hi] = np.arange(lo, hi)
    data = wh.fold_case(table[data], latin=True).astype(np.uint32)
    if len(data) < 3:
        return np.zeros(0, np.int64), np.zeros(len(offsets), np.int64)
    code = data[:-2] | data[1:-1] << 8 | data[2:] << 16
    return ((code * np.uint32(2654435761)) >> np.uint32(19)).astype(np.int64), offsets


def _spans(offsets: np.ndarray, total: int) -> tuple[np.ndarray, np.ndarray]:
    start = np.minimum(offsets[:-1], total)
    return start, np.maximum(start, np.minimum(offsets[1:] - 2, total))


def count_grams(texts) -> np.ndarray:
    code, offsets = _grams(texts)
    start, end = _spans(offsets, len(code))
    return np.stack([np.bincount(code[a:b], minlength=GRAMS) for a, b in zip(start, end, strict=True)]) if len(start) else np.zeros((0, GRAMS), np.int64)


Sparse = tuple[np.ndarray, np.ndarray]


def train_svms(x: list[Sparse], y: np.ndarray, *, epochs: int = 12, ridge: float = 1e-4, seed: int = 3) -> tuple[np.ndarray, np.ndarray]:
    """Linear SVMs, a column of y (-1 or 1) each, by stochastic subgradients on hinge loss, averaged over the last half.
    x: (places, values) of each row. The two sides of a machine weigh alike. Weights (grams x machines) and biases."""
    rnd, rows, machines = np.random.default_rng(seed), *y.shape
    weight = np.where(y > 0, 0.5 / np.maximum(1, (y > 0).sum(0)), 0.5 / np.maximum(1, (y < 0).sum(0))) * rows * y
    w, b, shrunk = np.zeros((GRAMS, machines)), np.zeros(machines), 1.0  # the weights are shrunk * w
    sw, sb, n, t = np.zeros_like(w), np.zeros_like(b), 0, 0
    for epoch in range(epochs):
        for i in rnd.permutation(rows):
            t += 1
            at, value = x[i]
            pull = np.where(y[i] * (shrunk * (value @ w[at]) + b) < 1, weight[i], 0.0)
            if pull.any():
                w[at] += np.outer(value, pull * (100 / (t + 1000) / shrunk))
                b += 0.01 * pull
            shrunk *= 1 - ridge
        w, shrunk = w * shrunk, 1.0
        if epoch >= epochs // 2:
            sw, sb, n = sw + w, sb + b, n + 1
    return sw / max(1, n), sb / max(1, n)


@dataclass
class Model:
    """Machines: (weights, bias) in whole numbers. family: one a family; pair: (language, other) -> machine for the first.
    common: the language with the most rows to learn from."""

    languages: dict[str, list[str]] = field(default_factory=dict)
    family: dict[str, tuple[np.ndarray, int]] = field(default_factory=dict)
    pair: dict[tuple[str, str], tuple[np.ndarray, int]] = field(default_factory=dict)
    common: str = "und"

    def predict(self, texts) -> tuple[list[str], list[float]]:
        code, offsets = _grams(texts)
        start, end = _spans(offsets, len(code))
        length, n = np.maximum(end - start, 1), len(start)
        used = np.zeros(n, bool) if not len(code) else end > start

        def margin(machine: tuple[np.ndarray, int]) -> np.ndarray:
            w, b = machine
            run = np.concatenate([[0], np.cumsum(w[code])])
            return ((run[end] - run[start]) / length + b) / SCALE

        names = sorted(self.languages)
        if not names:
            return ["und"] * n, [0.0] * n
        by_family = np.stack([margin(self.family[f]) for f in names]) if len(names) > 1 else np.ones((1, n))
        won = by_family.argmax(0)
        sure = 1 / (1 + np.exp(-np.clip(by_family.max(0), -30, 30)))
        lang = np.empty(n, object)
        score = np.zeros(n)
        for k, f in enumerate(names):
            own, langs = np.flatnonzero(won == k), self.languages[f]
            if not len(own):
                continue
            votes, strength = np.zeros((len(langs), n)), np.zeros((len(langs), n))
            for (a, b), machine in self.pair.items():
                if a in langs and b in langs:
                    m = margin(machine)
                    i, j = langs.index(a), langs.index(b)
                    votes[i] += m > 0
                    votes[j] += m <= 0
                    strength[i] += m
                    strength[j] -= m
            best = (votes + 1e-6 * np.tanh(strength)).argmax(0)
            rest = 1 / (1 + np.exp(-np.clip(strength[best, np.arange(n)] / max(1, len(langs) - 1), -30, 30))) if len(langs) > 1 else np.ones(n)
            lang[own] = np.array(langs, object)[best[own]]
            score[own] = np.round(sure[own] * rest[own], 6)
        strings = texts.to_pylist()
        for d in range(n):
            if not _has_letter(strings[d]):
                lang[d], score[d] = "und", 0.0
            elif not used[d]:  # one or two letters: the language with the most texts learned
                lang[d] = self.common
        return lang.tolist(), score.tolist()


def _has_letter(text: str | None) -> bool:
    return bool(text) and (text[:64].isalpha() or any(map(str.isalpha, text)))


def fit(docs: DataFrame, *, per_language: int = 600, most_rows: int = 40_000, seed: int = 9) -> Model:
    """Learns from text and lang of rows that are not held out: at most per_language rows of each language and
    most_rows in all (one a language at least), picked by hash of doc_id. Every language that a label names is learned."""
    rows = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    narrow = rows.select("doc_id", "lang", F.xxhash64(F.lit(seed), "doc_id").alias("order"))
    most = {r.lang: k for k, r in enumerate(narrow.groupBy("lang").count().orderBy(F.desc("count"), "lang").collect())}
    per_language = max(1, min(per_language, most_rows // max(1, len(most))))
    # one id from each of many buckets: partial aggregation, whatever share of the rows a language has
    spread = narrow.groupBy("lang", F.pmod("order", F.lit(per_language)).alias("bucket")).agg(F.min(F.struct("order", "doc_id")).alias("p"))
    picked = spread.select("lang", "p.doc_id").withColumn("n", F.row_number().over(Window.partitionBy("lang").orderBy("doc_id"))).where(F.col("n") <= per_language).select("doc_id")
    texts = rows.join(F.broadcast(picked.distinct()), "doc_id").select("doc_id", "lang", "text")  # at most most_rows ids, or one a language

    def run(batches):
        for batch in batches:
            for part in wh.pieces(batch, "text"):
                c = count_grams(part.column("text"))
                packed = []
                for row in c:
                    at = np.flatnonzero(row)
                    packed.append(at.astype(np.uint16).tobytes() + row[at].astype(np.uint32).tobytes())
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("lang"), pa.array(packed, pa.binary())], ["doc_id", "lang", "grams"])

    found = sorted(texts.mapInArrow(run, f"doc_id {dict(docs.dtypes)['doc_id']}, lang string, grams binary").collect(), key=lambda r: (r.doc_id, r.lang, r.grams))
    found = [r for r in found if len(r.grams)]
    model = Model()
    if not found:
        return model
    x = []
    for r in found:
        n = len(r.grams) // 6
        at, c = np.frombuffer(r.grams, np.uint16, n).astype(np.int64), np.frombuffer(r.grams, np.uint32, n, 2 * n).astype(float)
        x.append((at, c / c.sum()))
    scale = 1 / max(1e-9, float(np.mean([np.sqrt((v**2).sum()) for _, v in x])))
    x = [(at, v * scale) for at, v in x]
    lang = np.array([r.lang for r in found], object)
    names = sorted(set(lang.tolist()), key=lambda c: (most[c], c))
    model.common = names[0]
    for c in names:
        model.languages.setdefault(FAMILIES.get(c, f"other {c}"), []).append(c)
    fam = np.array([FAMILIES.get(c, f"other {c}") for c in lang], object)
    whole = lambda w, b: (np.round(w * scale * SCALE).astype(np.int64), int(round(b * SCALE)))
    if len(model.languages) > 1:
        w, bias = train_svms(x, np.stack([np.where(fam == f, 1, -1) for f in model.languages], 1))
        model.family = {f: whole(w[:, k], bias[k]) for k, f in enumerate(model.languages)}
    for langs in model.languages.values():
        for i, a in enumerate(langs):
            for b in langs[i + 1 :]:
                own = np.flatnonzero((lang == a) | (lang == b))
                w, bias = train_svms([x[k] for k in own.tolist()], np.where(lang[own] == a, 1, -1)[:, None])
                model.pair[a, b] = whole(w[:, 0], bias[0])
    return model


def identify(docs: DataFrame, model: Model | None = None) -> DataFrame:
    """doc_id, held_out, lang_pred, score: one row per input row.

    'und' with score 0 for null text, text without a letter, or nothing to learn from.
    Null doc_id counts as not held out and is never learned from. Repeated rows get
    the same answer. An empty table gives no rows.
    """
    model = model or fit(docs)
    rows = docs.select("doc_id", F.col("text").cast("string").alias("text"))

    def run(batches):
        for batch in batches:
            for part in wh.pieces(batch, "text", 2 << 20):
                text = part.column("text")
                lang, score = model.predict(text)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(lang, pa.string()), pa.array(score, pa.float64())], ["doc_id", "lang_pred", "score"])

    out = rows.mapInArrow(run, f"doc_id {dict(rows.dtypes)['doc_id']}, lang_pred string, score double")
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")
