"""Tokens and n-grams in built-in expressions."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: A token is a run of these. Fixed value.
LETTERS = "0-9a-zà-öø-ÿ"


def tokens(c: str | Column) -> Column:
    """Lower-cased runs of letters and digits."""
    c = F.col(c) if isinstance(c, str) else c
    return F.regexp_extract_all(F.lower(c), F.lit(f"[{LETTERS}]+"), F.lit(0))


def n_tokens(c: str | Column) -> Column:
    return F.size(tokens(c))


def held(df: DataFrame, **made: Column) -> DataFrame:
    """df with columns added behind a generator of one row. Unlike a projection it is never folded into what uses them,
    so that an array that a lambda reads is made once a row, not once an element."""
    return df.select("*", F.inline(F.array(F.struct(*[c.alias(n) for n, c in made.items()]))))


def once(value: Column, body: Callable[[Column], Column]) -> Column:
    """body of a value that is made once: a lambda's variable is never folded into what uses it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def spans(a: Column, n: int, pair: Callable[[Column, Column], Column]) -> Column:
    """What pair makes of the n elements from each position on, by spans of 1, 2, 4 and so on: a few passes whatever n is.
    The last two spans may overlap, so pair must identify what it covers or be idempotent."""

    def step(x: Column, k: int) -> Column:  # elements k places apart
        return F.zip_with(F.slice(x, F.lit(1), F.greatest(F.size(x) - k, F.lit(0))), F.slice(x, F.lit(k + 1), F.greatest(F.size(x), F.lit(0))), pair)

    def grow(x: Column, k: int) -> Column:
        if k == n:
            return x
        far = min(k, n - k)
        return once(step(x, far), lambda y: grow(y, k + far))

    return once(a, lambda x: grow(x, 1))


def gram_hashes(c: Column, n: int) -> Column:
    """Hash of the n tokens from each position on; empty if there are fewer."""
    return F.coalesce(spans(F.transform(c, lambda x: F.xxhash64(x)), n, lambda a, b: F.xxhash64(a, b)), F.array().cast("array<bigint>"))


def winnow(hashes: Column, window: int) -> Column:
    """Fingerprints: the least hash of every window of so many, each once; of fewer the least of all."""
    least = spans(hashes, window, lambda a, b: F.least(a, b))
    return F.array_distinct(F.when(F.size(hashes) >= window, least).otherwise(F.when(F.size(hashes) > 0, F.array(F.array_min(hashes))).otherwise(hashes)))


#: DuckDB's form of tokens(text).
TOKENS_SQL = f"list_filter(string_split_regex(lower({{}}), '[^{LETTERS}]+'), lambda x: x <> '')"
