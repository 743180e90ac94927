"""Substring deduplication by difference-cover anchors.

A cover D modulo v has, for all residues a and b, a shift s < v with a+s and
b+s both in D. Hashing the (n-v+1)-word windows at cover positions only is
therefore enough: two equal n-word runs share an anchor at the same place of
both. Anchors found in one document alone rule out every n-word window around
them; the few windows left are hashed in full and compared.

Data flow. Texts are dealt once into blocks by doc_id. Each block sends its
distinct anchor hashes, packed as binary, to hash buckets; a bucket sends back
what other documents have too. Blocks then send the n-word hashes of the
windows around such anchors with the smallest doc_id they hold; buckets answer
with the smallest doc_id overall. Repeats are merged within each block before
any shuffle, so a passage in a third of all documents costs one entry a block,
and no pair of documents is ever formed. Bucket and hash come from different
hashes, which widens the 64-bit comparison by the bits of the bucket.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from detectlab.llm import wordhash as wh
from detectlab.llm.frames import n_blocks

#: Perfect difference covers: period -> positions. Fixed values.
COVERS = {3: (0, 1), 7: (0, 1, 3), 13: (0, 1, 3, 9)}
U = np.uint64


def cover_for(window: int) -> tuple[int, tuple[int, ...]]:
    """The largest cover that leaves anchors of at least half the window."""
    fits = [v for v in COVERS if window - v + 1 >= max(2, window // 2)]
    return (max(fits), COVERS[max(fits)]) if fits else (1, (0,))


def _pack(*arrays: np.ndarray) -> bytes:
    return b"".join([len(arrays[0]).to_bytes(8, "little"), *(np.ascontiguousarray(a).tobytes() for a in arrays)])


def _unpack(blob: bytes, n: int) -> list[np.ndarray]:
    size = int.from_bytes(blob[:8], "little")
    return [np.frombuffer(blob, np.int64 if k else U, size, 8 + 8 * size * k) for k in range(n)]


def _by_bucket(h: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """Order that groups h by bucket, and the bucket limits."""
    b = ((wh.mix(h ^ U(0x5851F42D4C957F2D)) >> U(33)) % U(buckets)).astype(np.int32)
    order = np.argsort(b, kind="stable")
    return order, np.searchsorted(b[order], np.arange(buckets + 1))


def _positions(first: np.ndarray, length: int, period: int, cover: tuple[int, ...]) -> np.ndarray:
    """Word indexes at which an anchor of length words starts, by place in its text."""
    counts = np.diff(first)
    place = np.arange(int(first[-1])) - np.repeat(first[:-1], counts)
    room = np.repeat(first[1:], counts) - np.arange(int(first[-1]))
    return np.flatnonzero(np.isin(place % period, cover) & (room >= length))


def _anchors(table, window: int) -> tuple[wh.Words, np.ndarray, np.ndarray]:
    period, cover = cover_for(window)
    words = wh.words_of(table.column("text"), seed=11)
    at = _positions(words.first, window - period + 1, period, cover)
    return words, at, wh.window_hash(words.hash, window - period + 1, 1)[at]


def _distinct(h: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct h, the smallest id of each, and whether it has several."""
    order = np.argsort(h, kind="stable")
    h, ids = h[order], ids[order]
    head = np.flatnonzero(np.r_[True, h[1:] != h[:-1]]) if len(h) else np.zeros(0, np.int64)
    if not len(h):
        return h, ids, np.zeros(0, bool)
    low, high = np.minimum.reduceat(ids, head), np.maximum.reduceat(ids, head)
    return h[head], low, low != high


def _send(h: np.ndarray, block: int, buckets: int, *more: np.ndarray) -> Iterator[tuple[int, int, bytes]]:
    order, edge = _by_bucket(h, buckets)
    for b in np.flatnonzero(np.diff(edge)):
        part = order[edge[b] : edge[b + 1]]
        yield int(b), block, _pack(h[part], *(m[part] for m in more))


def _rows(rows: list[tuple[int, int, bytes]]) -> pa.RecordBatch:
    to, of, blob = zip(*rows, strict=True) if rows else ((), (), ())
    return pa.RecordBatch.from_arrays([pa.array(to, pa.int32()), pa.array(of, pa.int32()), pa.array(blob, pa.binary())], ["to", "of", "blob"])


_MESSAGE = "to int, of int, blob binary"


def _answer(batches: Iterator[pa.RecordBatch], answer) -> Iterator[pa.RecordBatch]:
    """answer(list of (block, blob)) for the blobs of each bucket of this partition."""
    held: dict[int, list[tuple[int, bytes]]] = {}
    for batch in batches:
        for to, of, blob in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True):
            held.setdefault(to, []).append((of, blob))
    for bucket in sorted(held):
        yield _rows([(of, bucket, blob) for of, blob in answer(sorted(held.pop(bucket)))])


def _shared_anchors(parts: list[tuple[int, bytes]]):
    """Hashes that two documents have: two blocks, or one block that says so itself."""
    own = [_unpack(blob, 2) for _, blob in parts]
    h = np.concatenate([x[0] for x in own])
    several = np.concatenate([x[1] for x in own])
    order = np.argsort(h, kind="stable")
    s = h[order]
    head = np.flatnonzero(np.r_[True, s[1:] != s[:-1]])
    times = np.diff(np.append(head, len(s))) + np.add.reduceat(several[order], head)
    common = s[head][times > 1]
    for (block, _), (mine, _) in zip(parts, own, strict=True):
        got = mine[np.isin(mine, common)]
        if len(got):
            yield block, _pack(got)


def _smallest_ids(parts: list[tuple[int, bytes]]):
    """For each block, its hashes whose smallest doc_id is below one that the block holds."""
    own = [_unpack(blob, 3) for _, blob in parts]
    h, low = np.concatenate([x[0] for x in own]), np.concatenate([np.cumsum(x[1]) for x in own])
    order = np.argsort(h, kind="stable")
    s = h[order]
    head = np.flatnonzero(np.r_[True, s[1:] != s[:-1]])
    keys, least = s[head], np.minimum.reduceat(low[order], head)
    for (block, _), (mine, delta, several) in zip(parts, own, strict=True):
        best = least[np.searchsorted(keys, mine)]
        use = (best < np.cumsum(delta)) | (several > 0)
        if use.any():
            order = np.argsort(best[use], kind="stable")
            yield block, _pack(mine[use][order], np.diff(best[use][order], prepend=0))


def mark_repeats(docs: DataFrame, window: int = 13, finish=None, result: str | None = None) -> DataFrame:
    """Words of each text that lie in a window that a smaller doc_id starts too.

    docs: doc_id, text and any others, which are ignored. Result, one row per
    input row: doc_id, n_words, n_removed, kept_sha256, kept_text.
    finish(table, words, removed) with its result schema replaces the last columns.

    Null text is empty. Rows without doc_id are compared with nothing and lose
    nothing. Rows with the same doc_id never remove each other's words. Texts
    shorter than the window lose nothing. An empty table gives no rows.
    """
    finish, result = finish or _kept, result or "doc_id long, n_words long, n_removed long, kept_sha256 string, kept_text string"
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    blocks = n_blocks(docs)
    # rows without an id spread by their text
    dealt = docs.withColumn("to", F.pmod(F.xxhash64(F.coalesce(F.col("doc_id"), F.xxhash64("text"))), F.lit(blocks)).cast("int")).repartition(blocks, "to")

    def anchors(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            batch = pa.Table.from_batches([batch])
            for block in np.unique(batch.column("to").to_numpy()):
                own = batch.filter(pa.compute.and_(pa.compute.equal(batch.column("to"), int(block)), pa.compute.is_valid(batch.column("doc_id"))))
                got, ids = [], []
                for part in wh.pieces(own, "text"):
                    words, at, h = _anchors(part, window)
                    got.append(h)
                    ids.append(part.column("doc_id").to_numpy()[np.searchsorted(words.first, at, "right") - 1])
                if got:
                    h, _, several = _distinct(np.concatenate(got), np.concatenate(ids))
                    yield _rows(list(_send(h, int(block), blocks, several.astype(np.int64))))

    def windows(texts: pa.Table, common: pa.Table):
        block = int((texts if texts.num_rows else common).column("to")[0].as_py())
        out = []
        known = [_unpack(b, 1)[0] for b in common.column("blob").to_pylist()]
        if known and texts.num_rows:
            known = np.sort(np.concatenate(known))
            got, ids = [], []
            period, _ = cover_for(window)
            for part in wh.pieces(texts.filter(pa.compute.is_valid(texts.column("doc_id"))), "text"):
                words, at, h = _anchors(part, window)
                hit = at[_among(h, known)]
                total = int(words.first[-1])
                open_ = np.zeros(total + 1, np.int64)
                np.add.at(open_, np.maximum(hit - period + 1, 0), 1)
                np.add.at(open_, hit + 1, -1)
                near = np.flatnonzero(np.cumsum(open_[:-1]) > 0)
                near = near[near <= total - window]
                near = near[np.searchsorted(words.first, near, "right") == np.searchsorted(words.first, near + window - 1, "right")]
                got.append(wh.window_hash(words.hash, window, 2)[near])
                ids.append(part.column("doc_id").to_numpy()[np.searchsorted(words.first, near, "right") - 1])
            if got:
                h, low, several = _distinct(np.concatenate(got), np.concatenate(ids))
                order = np.argsort(low, kind="stable")
                h, low, several = h[order], low[order], several[order]
                pos, edge = _by_bucket(h, blocks)
                for b in np.flatnonzero(np.diff(edge)):
                    p = pos[edge[b] : edge[b + 1]]
                    out.append((int(b), block, _pack(h[p], np.diff(low[p], prepend=0), several[p].astype(np.int64))))
        return pa.Table.from_batches([_rows(out)])

    def remove(texts: pa.Table, least: pa.Table):
        if not texts.num_rows:
            return finish(texts, None, None, [])
        known = [_unpack(b, 2) for b in least.column("blob").to_pylist()]
        h = np.concatenate([x[0] for x in known]) if known else np.zeros(0, U)
        low = np.concatenate([np.cumsum(x[1]) for x in known]) if known else np.zeros(0, np.int64)
        order = np.argsort(h, kind="stable")
        h, low = h[order], low[order]
        outs = []
        for part in wh.pieces(texts, "text"):
            words = wh.words_of(part.column("text"), seed=11)
            total = int(words.first[-1])
            gone = np.zeros(total, bool)
            if len(h) and total >= window:
                wins = wh.window_hash(words.hash, window, 2)
                at = np.searchsorted(h, wins)
                at[at == len(h)] = 0
                found = np.flatnonzero((h[at] == wins) & wh.window_ok(words.first, window))
                column = part.column("doc_id")
                owner = np.searchsorted(words.first, found, "right") - 1
                ids = pa.compute.fill_null(column, np.iinfo(np.int64).min).to_numpy()
                found = found[low[at[found]] < ids[owner]]
                depth = np.zeros(total + 1, np.int64)
                np.add.at(depth, found, 1)
                np.add.at(depth, found + window, -1)
                gone = np.cumsum(depth[:-1]) > 0
            outs.append(finish(part, words, gone, outs))
        return pa.concat_tables(outs)

    def to_common(batches):
        return _answer(batches, _shared_anchors)

    def to_least(batches):
        return _answer(batches, _smallest_ids)

    sent = dealt.mapInArrow(anchors, _MESSAGE).repartition(blocks, "to")
    common = sent.mapInArrow(to_common, _MESSAGE)
    asked = dealt.groupBy("to").cogroup(common.groupBy("to")).applyInArrow(windows, _MESSAGE).repartition(blocks, "to")
    least = asked.mapInArrow(to_least, _MESSAGE)
    return dealt.groupBy("to").cogroup(least.groupBy("to")).applyInArrow(remove, result)


def _among(h: np.ndarray, known: np.ndarray) -> np.ndarray:
    at = np.searchsorted(known, h)
    at[at == len(known)] = 0
    return known[at] == h


def _kept(table, words, gone, _outs) -> pa.Table:
    names = ["doc_id", "n_words", "n_removed", "kept_sha256", "kept_text"]
    if words is None:
        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string()]
        return pa.table([pa.array([], k) for k in kinds], names)
    raw, left = words.data.tobytes(), []
    removed = np.add.reduceat(np.append(gone, False).astype(np.int64), words.first[:-1]) * (words.counts > 0)
    stays = np.flatnonzero(~gone)
    edge = np.searchsorted(stays, words.first)
    s, e = words.start[stays].tolist(), words.end[stays].tolist()
    for k in range(len(words.first) - 1):
        a, b = int(edge[k]), int(edge[k + 1])
        left.append(b" ".join([raw[x:y] for x, y in zip(s[a:b], e[a:b], strict=True)]))
    sha = [hashlib.sha256(x).hexdigest() for x in left]
    return pa.table([table.column("doc_id"), pa.array(words.counts, pa.int64()), pa.array(removed, pa.int64()), pa.array(sha, pa.string()), pa.array([x.decode() for x in left], pa.string())], names)
