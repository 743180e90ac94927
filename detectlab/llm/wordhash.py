"""Vectorised word hashing over Arrow string arrays.

A batch of texts is hashed straight from its UTF-8 buffer: no Python object is
made per word. Byte-level work runs in slices of about ``slice_bytes``, cut at
separators, so memory follows the word count rather than the byte count.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U = np.uint64
_STEP = U(0x9E3779B97F4A7C15)
_POWER = U(0xD6E8FEB86659FD93)


def mix(x: np.ndarray) -> np.ndarray:
    """Bijective 64-bit finaliser (xor-shift-multiply)."""
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


def _table(seed: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        return mix(np.arange(1, 257, dtype=U) * _STEP + U(seed))


def separators(*, letters_only: bool = False) -> np.ndarray:
    """True for bytes that end a word: ASCII white space, or all ASCII but letters and digits."""
    sep = np.zeros(256, bool)
    if letters_only:
        sep[:128] = True
        for lo, hi in ((48, 58), (65, 91), (97, 123)):
            sep[lo:hi] = False
    else:
        sep[[9, 10, 11, 12, 13, 32]] = True
    return sep


@dataclass
class Words:
    """hash: one value a word. first: index of each text's first word, and the total. start, end: byte offsets."""

    hash: np.ndarray
    first: np.ndarray
    start: np.ndarray
    end: np.ndarray
    data: np.ndarray

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def texts(self) -> np.ndarray:
        """Index of the text of each word."""
        return np.repeat(np.arange(len(self.first) - 1), self.counts)


def buffer_of(texts) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes and offsets; nulls are empty."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks() if texts.num_chunks != 1 else texts.chunk(0)
    texts = texts.cast(pa.large_string()).fill_null("")
    if not len(texts):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offs, data = texts.buffers()
    offsets = np.frombuffer(offs, np.int64, len(texts) + 1, texts.offset * 8)
    base, last = int(offsets[0]), int(offsets[-1])
    raw = np.frombuffer(data, np.uint8, last - base, base) if last > base else np.zeros(0, np.uint8)
    return raw, offsets - base


def fold_case(data: np.ndarray, latin: bool = False) -> np.ndarray:
    """Lower-case A-Z; with latin also the letters U+00C0 to U+00DE."""
    table = np.arange(256, dtype=np.uint8)
    table[65:91] += 32
    out = table[data]
    if latin and len(out) > 1:
        up = (out[:-1] == 0xC3) & (out[1:] >= 0x80) & (out[1:] <= 0x9E) & (out[1:] != 0x97)
        out[1:][up] += 32
    return out


def words_of(texts, *, fold: str | None = None, letters_only: bool = False, seed: int = 1, slice_bytes: int = 1 << 21) -> Words:
    """Words of every text. fold: None, 'ascii' or 'latin'."""
    data, offsets = buffer_of(texts)
    if fold:
        data = fold_case(data, fold == "latin")
    sep, value = separators(letters_only=letters_only), _table(seed)
    power = np.ones(1, U)
    hashes, starts, ends, at, total = [], [], [], 0, len(data)
    with np.errstate(over="ignore"):
        while at < total:
            cut = min(total, at + slice_bytes)
            while cut < total:  # go on to a separator
                ahead = np.flatnonzero(sep[data[cut : cut + 65536]])
                if len(ahead):
                    cut += int(ahead[0])
                    break
                cut = min(total, cut + 65536)
            piece = data[at:cut]
            inside = ~sep[piece]
            begins = inside.copy()
            begins[1:] &= ~inside[:-1]
            edges = offsets[np.searchsorted(offsets, at) : np.searchsorted(offsets, cut)] - at
            begins[edges] = inside[edges]
            where = np.flatnonzero(inside)
            if len(where):
                head = np.flatnonzero(begins[where])
                lens = np.diff(np.append(head, len(where)))
                longest = int(lens.max())
                if longest > len(power):
                    power = np.cumprod(np.concatenate([np.ones(1, U), np.full(longest + 64, _POWER)]))
                place = np.arange(len(where)) - np.repeat(head, lens)
                h = np.add.reduceat(value[piece[where]] * power[place], head)
                hashes.append(mix(h ^ (lens.astype(U) * _STEP)))
                s = where[head] + at
                starts.append(s)
                ends.append(s + lens)
            at = cut
    none = np.zeros(0, np.int64)
    start = np.concatenate(starts) if starts else none
    return Words(np.concatenate(hashes) if hashes else np.zeros(0, U), np.searchsorted(start, offsets), start, np.concatenate(ends) if ends else none, data)


def window_hash(words: np.ndarray, n: int, seed: int = 0) -> np.ndarray:
    """Hash of the n words from each position on; length len(words) - n + 1, across text borders."""
    size = len(words) - n + 1
    if size <= 0:
        return np.zeros(0, U)
    with np.errstate(over="ignore"):
        out = np.zeros(size, U)
        for j in range(n):
            factor = mix(np.array([j + 1 + 1000 * (seed + 1)], U) * _STEP)[0] | U(1)
            out += words[j : j + size] * factor
        return mix(out + U(n))


def window_ok(first: np.ndarray, n: int) -> np.ndarray:
    """Which of window_hash's positions lie in one text."""
    size = int(first[-1]) - n + 1
    if size <= 0:
        return np.zeros(0, bool)
    ok = np.ones(size, bool)
    for edge in first[1:-1]:
        ok[max(0, edge - n + 1) : edge] = False
    return ok


def pieces(table: pa.Table | pa.RecordBatch, column: str, limit: int = 4 << 20):
    """Row slices of about limit bytes of text, one row at least."""
    n = table.num_rows
    if not n:
        return
    size = pc.fill_null(pc.binary_length(table.column(column)), 0)
    offsets = np.concatenate([[0], np.cumsum(size.to_numpy(zero_copy_only=False) if isinstance(size, pa.Array) else size.to_numpy(), dtype=np.int64)])
    at = 0
    while at < n:
        to = int(np.searchsorted(offsets, offsets[at] + limit, "right")) - 1
        to = min(n, max(at + 1, to))
        yield table.slice(at, to - at)
        at = to
    pa.default_memory_pool().release_unused()
