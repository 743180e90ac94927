"""Quality rules whose limits come from the corpus itself.

Each document gets a few counts. For every language and source a mergeable
quantile sketch of each measure is kept: a count per bin, with 128 bins for each
power of two, so that sketches add up across partitions, days or sources and a
quantile is off by less than 1 %. Limits are fences from the sketch of (language,
source), or of the language, or of everything where a group is small: a quantile
plus a multiple of its distance to another one of the same sketch. No limit has a
fixed part. Shares of words, lines and characters are taken at their lower bound, the
count less three times its square root, so that a few by chance in a short
text say nothing. A group that holds little but copies of a few texts has hardly any spread of its
own; at least a stated part of what is usual within groups, of its language and of all, is taken.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from detectlab.llm import wordhash as wh
from detectlab.llm.frames import cut

SYMBOLS = "#*$%&|<>"  # fixed values
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines")
#: measure -> what it counts in ten-thousandths, and of what
MEASURES = {"symbol_share": ("n_symbols", "word_chars"), "dup_line_share": ("n_dup_lines", "n_lines"), "repeat_share": ("n_repeat_words", "n_words"), "word_length": ("word_chars", "n_words")}
SHARES = ("symbol_share", "dup_line_share", "repeat_share")


@dataclass(frozen=True)
class Fence:
    """The upper limit is ``reach`` times the distance of two quantiles (in per cent) above the higher one.
    below: there is a lower limit likewise."""

    low: int
    high: int
    reach: int
    below: bool = False


@dataclass(frozen=True)
class Rules:
    """min_words, max_repeat: base rules. fences: by measure, in the order of MEASURES. least_spread: per cent of the
    median spread within groups, of its language and of all, that a group has at least. min_group: documents that a group's own sketch
    must hold. broadcast_rows: limits above which the join shuffles instead."""

    min_words: int = 50
    max_repeat: int = 50
    fences: tuple[Fence, ...] = (Fence(25, 75, 3), Fence(50, 90, 3), Fence(50, 99, 3), Fence(25, 75, 5, below=True))
    least_spread: int = 50
    min_group: int = 100
    broadcast_rows: int = 100_000


def _counts(texts: pa.Array) -> np.ndarray:
    words = wh.words_of(texts)
    n, total = len(texts), int(words.first[-1])
    out = np.zeros((6, n), np.int64)
    out[0] = words.counts
    data, offsets = wh.buffer_of(texts)
    for row, table in ((1, ~wh.separators()), (2, np.zeros(256, bool))):
        if row == 1:
            table[0x80:0xC0] = False  # not the first byte of a code point
        else:
            table[[ord(c) for c in SYMBOLS]] = True
        at = np.flatnonzero(table[data]) if len(data) else np.zeros(0, np.int64)
        out[row] = np.diff(np.searchsorted(at, offsets))
    if total >= 3:
        h = wh.window_hash(words.hash, 3)
        ok = np.flatnonzero(wh.window_ok(words.first, 3))
        owner = np.searchsorted(words.first, ok, "right") - 1
        with np.errstate(over="ignore"):
            key = h[ok] ^ wh.mix(owner.astype(np.uint64) + np.uint64(77))
        order = np.argsort(key, kind="stable")
        s = key[order]
        twin = np.zeros(len(s), bool)
        same = s[1:] == s[:-1]
        twin[1:] |= same
        twin[:-1] |= same
        found, depth = ok[order[twin]], np.zeros(total + 3, np.int64)
        np.add.at(depth, found, 1)
        np.add.at(depth, found + 3, -1)
        covered = np.flatnonzero(np.cumsum(depth)[:total] > 0)
        out[4] = np.diff(np.searchsorted(covered, words.first))
    for k, text in enumerate(texts.to_pylist()):
        if text and "\n" in text:
            lines = [x for x in text.split("\n") if x and x.strip(" \t\n\r\x0b\x0c")]
            out[5, k], out[3, k] = len(lines), len(lines) - len(set(lines))
        else:
            out[5, k] = int(out[0, k] > 0)
    return out


def with_counts(docs: DataFrame) -> DataFrame:
    """doc (all columns as a struct, so that names can't clash) and COUNTS."""
    def run(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for text in texts:
            table = pa.table([text], ["text"])
            got = [_counts(p.column("text").combine_chunks()) for p in wh.pieces(table, "text", 2 << 20)]
            values = np.concatenate(got, axis=1) if got else np.zeros((len(COUNTS), 0), np.int64)
            yield pa.StructArray.from_arrays([pa.array(x, pa.int64()) for x in values], list(COUNTS))

    # only the text goes to Python and only counts come back; not deterministic, so that no filter runs it twice
    count = F.arrow_udf(run, ", ".join(f"{c} long" for c in COUNTS)).asNondeterministic()
    held = docs.select(F.struct("*").alias("doc"), count(F.col("text").cast("string")).alias("counts"))
    return held.select("doc", *[F.col(f"counts.{c}").alias(c) for c in COUNTS])


def base_failed(rules: Rules) -> Column:
    return (F.col("n_words") < rules.min_words) | (F.lit(100) * F.col("n_repeat_words") > F.lit(rules.max_repeat) * F.col("n_words"))


def measure(name: str) -> Column:
    part, whole = MEASURES[name]
    counted = f"greatest({part} - cast(ceil(3 * sqrt({part})) as long), 0)" if name in SHARES else part
    return F.expr(f"10000 * {counted} div greatest({whole}, 1)")


def bin_of(value: Column) -> Column:
    """Sketch bin: the value itself below 256, else its eight leading bits and how many follow."""
    follow = F.greatest(F.length(F.bin(value)) - 8, F.lit(0))
    return (follow * 128 + F.call_function("shiftright", value, follow)).cast("long")


def floor_of(b: Column) -> Column:
    """The smallest value of a bin."""
    return F.when(b < 256, b).otherwise(F.call_function("shiftleft", b % 128 + 128, (F.floor(b / 128) - 1).cast("int")))


def group_key(column: str) -> Column:
    return F.coalesce(F.concat(F.lit("="), F.col(column)), F.lit("-"))


def sketches(counted: DataFrame, rules: Rules) -> DataFrame:
    """(level, lang_key, source_key, measure, bin, docs). level 0: language and source, 1: language, 2: all.
    counted: lang, source and COUNTS; documents that fail the base rules are left out."""
    named = F.array(*[F.struct(F.lit(m).alias("measure"), bin_of(measure(m)).alias("bin")) for m in MEASURES])
    fine = (
        counted.where(~base_failed(rules))
        .select(group_key("lang").alias("lang_key"), group_key("source").alias("source_key"), F.inline(named))
        .groupBy("lang_key", "source_key", "measure", "bin")
        .agg(F.count("*").alias("docs"))
    )
    levels = F.array(
        *[F.struct(F.lit(n).alias("level"), a.alias("lang_key"), b.alias("source_key")) for n, a, b in ((0, F.col("lang_key"), F.col("source_key")), (1, F.col("lang_key"), F.lit("")), (2, F.lit(""), F.lit("")))]
    )
    return fine.select("measure", "bin", "docs", F.inline(levels)).groupBy("level", "lang_key", "source_key", "measure", "bin").agg(F.sum("docs").alias("docs"))


def _by_measure(values: dict[str, object]) -> Column:
    return F.create_map(*[F.lit(x) for kv in values.items() for x in kv])[F.col("measure")]


def quantiles(sketch: DataFrame, rules: Rules) -> DataFrame:
    """(level, lang_key, source_key, measure, n, q_low, q_high): the two quantiles of the measure's fence, each from the smallest bin that holds the rank: its least value and its greatest."""
    keys = ["level", "lang_key", "source_key", "measure"]
    held = sketch.groupBy(*keys).agg(F.sum("docs").alias("n"), F.array_sort(F.collect_list(F.struct("bin", "docs"))).alias("bins"))
    fences = dict(zip(MEASURES, rules.fences, strict=True))

    def bin_at(q: Column) -> Column:  # the bins of one group are at most 256 + 128 * 56
        walked = F.aggregate(
            "bins",
            F.struct(F.lit(0).cast("long").alias("seen"), F.lit(None).cast("long").alias("hit")),
            lambda acc, x: F.struct((acc.seen + x.docs).alias("seen"), F.coalesce(acc.hit, F.when((acc.seen + x.docs) * 100 >= F.col("n") * q, x.bin)).alias("hit")),
        )
        return walked.hit

    return held.select(*keys, "n", floor_of(bin_at(_by_measure({m: f.low for m, f in fences.items()}))).alias("q_low"), (floor_of(bin_at(_by_measure({m: f.high for m, f in fences.items()})) + 1) - 1).alias("q_high"))


def limits(found: DataFrame, rules: Rules) -> DataFrame:
    """lang_key, source_key, level and a struct (low, high) a measure: one row per group of level 0, and the wider levels. found: quantiles()."""
    fences = dict(zip(MEASURES, rules.fences, strict=True))
    own = F.col("q_high") - F.col("q_low")
    groups = found.where((F.col("level") == 0) & (F.col("n") >= rules.min_group)).withColumn("own", own)
    least = F.floor(F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY own)") * rules.least_spread / 100)
    usual = found.join(groups.groupBy("lang_key", "measure").agg(least.alias("of_lang")), ["lang_key", "measure"], "left")
    usual = usual.join(F.broadcast(groups.groupBy("measure").agg(least.alias("of_all"))), "measure", "left")  # a row a measure
    width = F.greatest(own, "of_lang", "of_all") * _by_measure({m: f.reach for m, f in fences.items()})
    low = F.when(_by_measure({m: f.below for m, f in fences.items()}), F.col("q_low") - width).otherwise(F.lit(-1))
    q = usual.select("level", "lang_key", "source_key", "measure", "n", (F.col("q_high") + width).alias("high"), low.alias("low"))
    by = {m: F.max(F.when(F.col("measure") == m, F.struct("low", "high"))).alias(m) for m in MEASURES}
    return q.groupBy("level", "lang_key", "source_key").agg(F.max("n").alias("n"), *by.values()).where((F.col("level") == 2) | (F.col("n") >= rules.min_group))


def verdicts(docs: DataFrame, rules: Rules = Rules()) -> DataFrame:
    """doc (struct of all columns), COUNTS, base_failed, kept. One row per input row.

    Null or empty text has no words and fails. Null language or source is a group
    of its own. Repeated rows count each. A measure equal to its limit is within it; where both quantiles
    of a fence tie, there and in most groups, they are the limit. An empty table gives no rows.
    """
    counted = with_counts(docs)
    narrow = counted.select("doc.lang", "doc.source", *COUNTS)
    found = cut(limits(cut(quantiles(sketches(narrow, rules), rules)), rules))
    few = found.count() <= rules.broadcast_rows
    small = (lambda d: F.broadcast(d)) if few else (lambda d: d)
    out = counted.withColumns({"lang_key": group_key("doc.lang"), "source_key": group_key("doc.source"), "base_failed": base_failed(rules)} | {m: measure(m) for m in MEASURES})
    for level, keys in ((0, ["lang_key", "source_key"]), (1, ["lang_key"]), (2, [])):
        side = found.where(F.col("level") == level).select(*keys, F.struct(*MEASURES).alias(f"limit{level}"))
        out = out.join(small(side), keys, "left") if keys else out.join(F.broadcast(side), F.lit(True), "left")  # level 2 is one row
    limit = F.coalesce("limit0", "limit1", "limit2")
    fits = F.lit(True)
    for m in MEASURES:
        fits = fits & F.coalesce(F.col(m).between(limit[m]["low"], limit[m]["high"]), F.lit(True))
    return out.select("doc", *COUNTS, "base_failed", (~F.col("base_failed") & fits).alias("kept"))


def filter_quality(docs: DataFrame, rules: Rules = Rules()) -> DataFrame:
    """The rows that pass, with the columns of docs."""
    return verdicts(docs, rules).where("kept").select("doc.*")
