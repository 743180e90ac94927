"""Benchmark decontamination by edit distance over words.

An item of L words is found in a document where some run of words is within
floor(L * percent / 100) word edits of it. The steps:

1. Words are letters and digits, lower-cased. Places where a document shares
   three-word grams with an item are kept if there are as many of them close by as
   a match within the limit must leave (q-gram lemma), so nothing is lost here.
   Items so short that none need be left have grams of two words or one.
2. Windows of the item's size at those places are embedded by a random walk that
   turns edit distance into Hamming distance: both strings are read by the same
   random bits, one a position and word, that say whether to step on.
3. Coordinates of the embedded strings are sampled, again and again; a window is a
   candidate for the items in the same bucket of any repetition. Their number
   follows from the recall asked for.
4. Candidates are verified by the exact edit distance, ends of the window free.

Items are read in blocks of a bounded number of words, each block against all documents.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from detectlab.llm import wordhash as wh

U = np.uint64
GRAM = 3


@dataclass(frozen=True)
class Search:
    """percent: edits in a hundred words of the item. recall: aimed at, of each window within the limit.
    sampled: coordinates a bucket. stretch: Hamming distance of embedded strings expected for an edit.
    min_words: shorter items would match ordinary prose and are left out. block_words: of items, read at once."""

    percent: int = 20
    recall: float = 0.999
    sampled: int = 3
    stretch: float = 6.0
    min_words: int = 5
    block_words: int = 2_000_000
    seed: int = 5

    def edits(self, size: int) -> int:
        return size * self.percent // 100

    def gram(self, size: int) -> int:
        """Words a gram: three, or fewer so that one must survive the edits."""
        return next((g for g in range(GRAM, 1, -1) if size - g + 1 - g * self.edits(size) >= 1), 1)

    def grams(self, size: int) -> int:
        """Places with a gram of the item that a match must leave."""
        g = self.gram(size)
        return max(1, size - g + 1 - g * self.edits(size))

    def repetitions(self, size: int) -> int:
        far = min(0.9, self.stretch * max(1, self.edits(size)) / (3 * size))
        return max(1, math.ceil(math.log(1 - self.recall) / math.log(1 - (1 - far) ** self.sampled)))


def embed(rows: np.ndarray, seed: int) -> np.ndarray:
    """Random-walk embedding of equally long rows of hashes into three times the length."""
    n, size = rows.shape
    padded = np.concatenate([rows, np.zeros((n, 1), U)], axis=1)
    at, out, who = np.zeros(n, np.int64), np.zeros((n, 3 * size), U), np.arange(n)
    with np.errstate(over="ignore"):
        for j in range(3 * size):
            here = padded[who, at]
            out[:, j] = here
            step = wh.mix(here + U(seed * 1_000_003 + j) * U(0x9E3779B97F4A7C15)) & U(1)
            at = np.minimum(at + step.astype(np.int64), size)
    return out


def buckets(rows: np.ndarray, how: Search) -> np.ndarray:
    """One bucket number a row and repetition; rows are windows or items of one length."""
    size, rep = rows.shape[1], how.repetitions(rows.shape[1])
    rnd = np.random.default_rng(how.seed * 7919 + size)
    out = np.zeros((len(rows), rep), U)
    walks = -(-rep // 4)  # an embedding serves four samplings
    with np.errstate(over="ignore"):
        for w in range(walks):
            y = embed(rows, how.seed + w)
            for r in range(w * 4, min(rep, w * 4 + 4)):
                h = np.full(len(rows), r, U)
                for c in rnd.choice(3 * size, how.sampled, replace=False):
                    h = wh.mix(h + y[:, c])
                out[:, r] = h
    return out


def best_edits(items: np.ndarray, regions: np.ndarray) -> np.ndarray:
    """Fewest word edits from each item (rows of one length) to any run of its region (rows padded with 0)."""
    pairs, width = regions.shape
    row, place = np.zeros((pairs, width + 1), np.int32), np.arange(width + 1, dtype=np.int32)
    for k in range(items.shape[1]):
        new = np.empty_like(row)
        new[:, 0] = k + 1
        np.minimum(row[:, :-1] + (regions != items[:, k : k + 1]), row[:, 1:] + 1, out=new[:, 1:])
        new -= place
        np.minimum.accumulate(new, axis=1, out=new)  # insertions
        new += place
        row = new
    return row.min(1)


def _read(words: np.ndarray, start: np.ndarray, stop: np.ndarray, size: int) -> np.ndarray:
    """Rows of size words from each start, 0 from stop on."""
    at = start[:, None] + np.arange(size)
    return np.where(at < stop[:, None], words[np.minimum(at, len(words) - 1)], U(0))


class Items:
    """Index of a block of items."""

    def __init__(self, rows: list[tuple[int, str]], how: Search):
        self.how = how
        w = wh.words_of(pa.array([t for _, t in rows], pa.string()), fold="latin", letters_only=True, seed=31)
        kept = [(i, w.hash[a:b]) for (i, _), a, b in zip(rows, w.first[:-1], w.first[1:], strict=True) if b - a >= how.min_words]
        self.ids, self.words = [i for i, _ in kept], [h for _, h in kept]
        self.size = np.array([len(h) for h in self.words], np.int64)
        self.edits = np.array([how.edits(n) for n in self.size.tolist()], np.int64)
        self.need = np.array([how.grams(n) for n in self.size.tolist()], np.int64)
        self.long = np.array([how.gram(n) for n in self.size.tolist()], np.int64)
        #: By words a gram: sorted grams, their items and places, and a bit for the low 20 of each gram.
        self.index: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = {}
        for n in np.unique(self.long).tolist():
            own = np.flatnonzero(self.long == n).tolist()
            grams = [wh.window_hash(self.words[k], n) for k in own]
            g = np.concatenate(grams)
            order = np.argsort(g, kind="stable")
            maybe = np.zeros(1 << 20, bool)
            maybe[(g & U((1 << 20) - 1)).astype(np.int64)] = True
            self.index[n] = g[order], np.repeat(own, [len(x) for x in grams])[order], np.concatenate([np.arange(len(x)) for x in grams])[order], maybe
        self.table: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        for n in np.unique(self.size).tolist():
            own = np.flatnonzero(self.size == n)
            b = buckets(np.stack([self.words[k] for k in own]), how)
            order = np.argsort(b.ravel(), kind="stable")
            self.table[n] = (b.ravel()[order], np.repeat(own, b.shape[1])[order])

    def _shared(self, w: wh.Words, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Place, text, item and where the item would start, of each gram of n words that a text shares with an item."""
        gram, of, offset, maybe = self.index[n]
        g = wh.window_hash(w.hash, n)
        near = np.flatnonzero(maybe[(g & U((1 << 20) - 1)).astype(np.int64)])
        low, high = np.searchsorted(gram, g[near], "left"), np.searchsorted(gram, g[near], "right")
        hit = high > low
        near, low, high = near[hit], low[hit], high[hit]
        text = np.searchsorted(w.first, near, "right") - 1
        inside = near + n <= w.first[text + 1]
        near, low, high, text = near[inside], low[inside], high[inside], text[inside]
        times = high - low
        pos, text = np.repeat(near, times), np.repeat(text, times)
        entry = np.repeat(low, times) + np.arange(len(pos)) - np.repeat(np.cumsum(times) - times, times)
        return pos, text, of[entry], pos - offset[entry]

    def matches(self, texts) -> Iterator[tuple[int, int, int, int]]:
        """(text, item, edits, first word of the window) for each text and item at most once: fewest edits, then first."""
        w = wh.words_of(texts, fold="latin", letters_only=True, seed=31)
        shared = [self._shared(w, n) for n in self.index]
        if not shared:
            return
        pos, text, item, start = (np.concatenate(x) for x in zip(*shared, strict=True))
        # places of one text and item, a gram counted once a place
        order = np.lexsort((start, pos, item, text))
        pos, text, item, start = pos[order], text[order], item[order], start[order]
        group = np.cumsum(np.r_[True, (text[1:] != text[:-1]) | (item[1:] != item[:-1])]) if len(pos) else np.zeros(0, np.int64)
        new = np.r_[True, (group[1:] != group[:-1]) | (pos[1:] != pos[:-1])] if len(pos) else np.zeros(0, bool)
        place = np.cumsum(new) - 1  # distinct places, numbered
        head = np.flatnonzero(new)
        gp, pp = group[head], pos[head]
        far = np.arange(len(head)) + self.need[item[head]] - 1
        ok = far < len(head)
        ok[ok] = (gp[far[ok]] == gp[ok]) & (pp[far[ok]] - pp[ok] <= (self.size + self.edits - self.long)[item[head]][ok])
        reach = np.zeros(len(head) + 1, np.int64)
        np.add.at(reach, np.flatnonzero(ok), 1)
        np.add.at(reach, far[ok] + 1, -1)
        live = (np.cumsum(reach[:-1]) > 0)[place] if len(head) else np.zeros(0, bool)
        windows = np.unique(np.stack([text[live], item[live], start[live]]), axis=1)
        if not windows.shape[1]:
            return
        text, item, start = windows
        first, last = w.first[text], w.first[text + 1]
        size = self.size[item]
        start = np.clip(start, first, np.maximum(first, last - size))
        found: dict[tuple[int, int], tuple[int, int]] = {}
        for n in np.unique(size).tolist():
            own = np.flatnonzero(size == n)
            slack = self.how.edits(n)
            keys, owner = self.table[n]
            for at in range(0, len(own), 4096):
                part = own[at : at + 4096]
                rows = _read(w.hash, start[part], last[part], n)
                b = buckets(rows, self.how)
                lo, hi = np.searchsorted(keys, b, "left"), np.searchsorted(keys, b, "right")
                hits = (hi - lo).ravel()
                window = np.repeat(np.arange(len(part)).repeat(b.shape[1]), hits)
                entry = np.repeat(lo.ravel(), hits) + np.arange(hits.sum()) - np.repeat(np.cumsum(hits) - hits, hits)
                window, cand = np.unique(np.stack([window, owner[entry]]), axis=1)
                for c in range(0, len(window), 2048):
                    win, item = window[c : c + 2048], cand[c : c + 2048]
                    k = part[win]
                    begin = np.maximum(first[k], start[k] - slack)
                    edits = best_edits(np.stack([self.words[i] for i in item.tolist()]), _read(w.hash, begin, np.minimum(last[k], start[k] + n + slack), n + 2 * slack))
                    for x in np.flatnonzero(edits <= slack).tolist():
                        mark, best = (int(text[k[x]]), int(item[x])), (int(edits[x]), int(start[k[x]] - first[k[x]]))
                        found[mark] = min(found.get(mark, best), best)
        for (t, i), (e, s) in sorted(found.items()):
            yield t, i, e, s


def item_blocks(benchmark: DataFrame, how: Search) -> Iterator[Items]:
    """Indexes of blocks of items, each of a bounded number of words. Null items are left out; equal items are one each."""
    named = benchmark.where("item_id is not null and text is not null").select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text"))
    words = named.agg(F.sum(F.size(F.split("text", r"\s+")))).first()[0] or 0
    blocks = max(1, -(-words // how.block_words))
    for k in range(blocks):
        rows = named.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == k).collect() if blocks > 1 else named.collect()
        yield Items(sorted({(r.item_id, r.text) for r in rows}), how)


def matches(docs: DataFrame, benchmark: DataFrame, how: Search = Search()) -> DataFrame:
    """doc_id, item_id, edits, item_words, at_word: one row for each row of docs and item found in it.

    Null and empty texts, and texts or items of fewer than min_words words, match
    nothing. Rows without doc_id are searched too. Repeated rows match each. Empty
    tables give no rows. at_word counts the document's words of letters and digits.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    schema = "doc_id long, item_id long, edits int, item_words int, at_word long"
    out = None
    for items in item_blocks(benchmark, how):

        def run(batches, items=items):
            for batch in batches:
                for part in wh.pieces(batch, "text", 16 << 20):
                    ids = part.column("doc_id").to_pylist()
                    rows = [(ids[t], items.ids[i], e, len(items.words[i]), s) for t, i, e, s in items.matches(part.column("text"))]
                    cols = zip(*rows, strict=True) if rows else ((),) * 5
                    yield pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(cols, (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64()), strict=True)], ["doc_id", "item_id", "edits", "item_words", "at_word"])

        found = docs.mapInArrow(run, schema)
        out = found if out is None else out.union(found)
    return out


def without_matches(docs: DataFrame, benchmark: DataFrame, how: Search = Search()) -> DataFrame:
    """The rows of docs in which no item is found, with their columns."""
    held = docs.select(F.struct("*").alias("doc"))
    for items in item_blocks(benchmark, how):
        held = held.select("doc", _found(items)(F.col("doc.text").cast("string")).alias("hit")).where("NOT hit").select("doc")
    return held.select("doc.*")


def _found(items: Items):
    """Whether a text holds an item. Only texts go to Python and only flags come back; not deterministic, so that it runs once."""

    def run(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for text in texts:
            hit, at = np.zeros(len(text), bool), 0
            for part in wh.pieces(pa.table([text], ["text"]), "text", 8 << 20):
                hit[[at + t for t, *_ in items.matches(part.column("text"))]] = True
                at += part.num_rows
            yield pa.array(hit)

    return F.arrow_udf(run, "boolean").asNondeterministic()
