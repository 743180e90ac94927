"""Exact n-gram Jaccard join: a size-aware mix of subset enumeration and list scans.

Sets are the distinct word shingles of each text. Equal sets are one node. Tokens
are ordered so that rare ones come first: by how many frequent words a shingle
holds, then by hash, and last the shingles that are frequent as a whole, by count.
Both frequent words and frequent shingles are bounded lists of heavy hitters; any
order gives the same result. A set of n tokens and a set like it share a token among the first
p = n - ceil(t n) + 1 of each, and two among the first p + 1.

* Small (light) sets enumerate the pairs of their first p + 1 tokens; like sets meet in a pair.
* Large (heavy) sets are filed under each of their first p tokens, and those lists are scanned.
* Light sets that a heavy one could be like are filed in the lists too.

The boundary is the size at which C(p + 1, 2) subsets cost more than scanning p
lists, from the sizes of all sets and the list lengths measured over all data.

Links are found without forming all pairs of a list. Two rounds compare each set with
a few of its lists only: its nearest neighbours in order of size, and the set in the
middle of the list; what is linked so forms components. Then sets of one list in
different components are compared: every set outside the list's largest component
with those in others. So a list whose members are one group costs nothing more, and
no link between components is lost. A distance that can't exceed the true one (of
token counts in 128 bins) rejects most pairs while lists are scanned; only the texts
of those left are read again, and each set of tokens goes to the one task that holds
its group of pairs. Long lists are scanned in blocks by blocks, groups with more
tokens than a task takes are compared so too.

Keys are never stored: texts are hashed a second time to file them, and only keys
that two different sets share are written.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from detectlab.llm import wordhash as wh
from detectlab.llm.components import components
from detectlab.llm.frames import cut, release

U = np.uint64
BINS = 128
_LAST = 9223372036854775807


@dataclass(frozen=True)
class Join:
    """words a shingle; percent: link when 100 * intersection >= percent * union. frequent: heavy hitters kept at
    most. frequent_share: share of a piece's documents from which a shingle counts as one. word_share: share of a
    piece's words from which a word is frequent; frequent_words: of these kept at most. light_cap: sizes from
    which the cost model takes a set for heavy anyway. list_run: members of a list compared at once. neighbours:
    places in a list that the first rounds look back. few_lists: lists of a set that they look at.
    broadcast_ids: documents to read again up to which their ids (16 bytes each) are broadcast. batch_rows: texts
    handed to Python at once. task_bytes: of tokens compared in one task. anchor_rows: of lists with the same least
    set in one task."""

    words: int = 5
    percent: int = 80
    frequent: int = 32768
    frequent_share: float = 0.002
    word_share: float = 0.0005
    frequent_words: int = 4096
    light_cap: int = 2000
    list_run: int = 10_000
    neighbours: int = 12
    few_lists: int = 4
    broadcast_ids: int = 1_000_000
    batch_rows: int = 1024
    task_bytes: int = 8 << 20
    anchor_rows: int = 10_000

    def prefix(self, n):
        return n - -(-self.percent * n // 100) + 1

    def alone(self, n):
        """No other set can be like one of this size."""
        return (self.prefix(n) == 1) & (100 * n // self.percent == n)


def shingle_sets(texts, words: int, frequent: np.ndarray | None = None) -> list:
    """The distinct shingle hashes of each text, in order. Fewer words than that are one shingle; none, an empty set.
    With frequent (sorted word hashes): pairs of these and the frequent words in each."""
    w = wh.words_of(texts, fold="ascii", seed=21)
    h, first = wh.window_hash(w.hash, words, 4), w.first
    out = []
    if frequent is not None:
        run = np.concatenate([[0], np.cumsum(_member(w.hash, frequent))])
        held = np.minimum(run[words:] - run[:-words], 6) if len(h) else run[:0]
    for a, b in zip(first[:-1].tolist(), first[1:].tolist(), strict=True):
        if b - a >= words:
            if frequent is None:
                out.append(np.unique(h[a : b - words + 1]))
            else:
                s, at = np.unique(h[a : b - words + 1], return_index=True)
                out.append((s, held[a + at]))
        else:
            s = wh.window_hash(w.hash[a:b], b - a, 4) if b > a else np.zeros(0, U)
            out.append(s if frequent is None else (s, np.zeros(len(s), np.int64)))
    return out


def _member(h: np.ndarray, known: np.ndarray) -> np.ndarray:
    if not len(known):
        return np.zeros(len(h), bool)
    at = np.searchsorted(known, h)
    at[at == len(known)] = 0
    return known[at] == h


def _counted(h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct values and how often each occurs."""
    h = np.sort(h)
    head = np.flatnonzero(np.r_[True, h[1:] != h[:-1]])
    return h[head], np.diff(np.append(head, len(h)))


def sketch_of(s: np.ndarray, bins: int = BINS) -> bytes:
    """Tokens in each bin, 255 at most."""
    return np.minimum(np.bincount((s >> U(20)).astype(np.int64) % bins, minlength=bins), 255).astype(np.uint8).tobytes()


def wide_sketch(s: np.ndarray) -> bytes | None:
    """A bin for four tokens or fewer, in powers of two; None where the small sketch is as good."""
    bins = 1 << max(0, len(s) - 1).bit_length() - 2 if len(s) > 4 else 0
    return sketch_of(s, bins) if bins > BINS else None


def _apart(x: bytes | None, y: bytes | None) -> int:
    """At most the number of tokens in one set only, from wide sketches; the longer one is folded."""
    if x is None or y is None:
        return 0
    a, b = (np.frombuffer(v, np.uint8).astype(np.int32) for v in (x, y))
    while len(a) != len(b):
        if len(a) > len(b):
            a = a[: len(a) // 2] + a[len(a) // 2 :]
        else:
            b = b[: len(b) // 2] + b[len(b) // 2 :]
    return int(np.abs(a - b).sum())


def _digest(s: np.ndarray) -> int:
    return int.from_bytes(hashlib.blake2b(s.tobytes(), digest_size=8).digest(), "little", signed=True)


def _texts(docs: DataFrame) -> DataFrame:
    """at (doc_id, or the largest long), mark (hash of the row's id and text), text."""
    at, text = F.coalesce(F.col("doc_id").cast("long"), F.lit(_LAST)), F.col("text").cast("string")
    return docs.select(at.alias("at"), F.xxhash64(at, text).alias("mark"), text.alias("text"))


def _column(part, name: str):
    got = part.column(name)
    return got if isinstance(part, pa.RecordBatch) else got.combine_chunks()


def survey(docs: DataFrame, how: Join) -> DataFrame:
    """One row per input row: at, mark, n, node (digest of the set; null if empty), sketch, wide
    (see sketch_of). Besides, with at null, counts of each piece of texts: kind, key, value."""
    schema = pa.schema([("at", pa.int64()), ("mark", pa.int64()), ("n", pa.int64()), ("node", pa.int64()), ("sketch", pa.binary()), ("wide", pa.binary()), ("kind", pa.int32()), ("key", pa.int64()), ("value", pa.int64())])

    def batch_of(size: int, **held) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([held.get(f.name, pa.nulls(size, f.type)) for f in schema], schema=schema)

    def run(batches):
        for batch in batches:
            for part in wh.pieces(batch, "text", 2 << 20):
                text = part.column("text")
                sets = shingle_sets(text, how.words)
                sketch, wide = [sketch_of(s) if len(s) else None for s in sets], [wide_sketch(s) for s in sets]
                node = pa.array([_digest(s) if len(s) else None for s in sets], pa.int64())
                yield batch_of(len(sets), at=_column(part, "at"), mark=_column(part, "mark"), n=pa.array([len(s) for s in sets], pa.int64()), node=node, sketch=pa.array(sketch, pa.binary()), wide=pa.array(wide, pa.binary()))
                sets = [s for s in sets if len(s)]
                if not sets:
                    continue
                words, times = _counted(wh.words_of(text, fold="ascii", seed=21).hash)
                often = times >= max(3, how.word_share * times.sum())
                shingles, lists = _counted(np.concatenate(sets))
                hot = lists >= max(3, how.frequent_share * len(sets))
                n, docs_of = np.unique(np.minimum([len(s) for s in sets], how.light_cap), return_counts=True)
                kind = np.repeat(np.array([0, 1, 2, 3, 4], np.int32), [hot.sum(), often.sum(), len(n), 1, 1])
                key = np.concatenate([shingles[hot].view(np.int64), words[often].view(np.int64), n.astype(np.int64), [0, 0]])
                value = np.concatenate([lists[hot], times[often], docs_of, [(lists.astype(float) ** 2).sum(), lists.sum()]]).astype(np.int64)
                yield batch_of(len(kind), kind=pa.array(kind), key=pa.array(key), value=pa.array(value))

    return _texts(docs).mapInArrow(run, "at long, mark long, n long, node long, sketch binary, wide binary, kind int, key long, value long")


def habits(surveyed: DataFrame, how: Join) -> tuple[np.ndarray, np.ndarray, int]:
    """Frequent shingles by count, frequent words in order of hash, and the largest size of a light set."""
    found = cut(surveyed.where("kind is not null").groupBy("kind", "key").agg(F.sum("value").alias("value")))
    top = lambda kind, most: np.array([r.key for r in found.where(F.col("kind") == kind).orderBy(F.desc("value"), "key").limit(most).collect()], np.int64).view(U)
    sizes = {r.key: r.value for r in found.where("kind = 2").collect()}
    scan = {r.kind: r.value for r in found.where("kind > 2").collect()}
    out = top(0, how.frequent), np.sort(top(1, how.frequent_words)), boundary(sizes, scan.get(3, 1) / max(1, scan.get(4, 1)), how)
    release(found)
    return out


def boundary(sizes: dict[int, int], scan: float, how: Join) -> int:
    """The size up to which enumerating pairs costs less than scanning lists of ``scan`` entries."""
    if not sizes:
        return 0
    n = np.array(sorted(sizes))
    docs = np.array([sizes[k] for k in n.tolist()], float)
    p = how.prefix(n)
    light, heavy = np.cumsum(docs * p * (p + 1) / 2), np.cumsum((docs * p * (1 + scan))[::-1])[::-1]
    best, at = np.inf, 0
    for limit in [0, *n[n < how.light_cap].tolist()]:
        k = np.searchsorted(n, limit, "right")
        low = np.searchsorted(n, how.percent * limit / 100, "right") if limit else 0
        cost = (light[k - 1] if k else 0) + (heavy[low] if low < len(n) else 0)
        if cost < best:
            best, at = cost, limit
    return int(at)


def _keys(s: np.ndarray, held: np.ndarray, hot: np.ndarray, rank: np.ndarray, light: int, how: Join) -> np.ndarray:
    n = len(s)
    if not n or how.alone(n):
        return np.zeros(0, np.int64)
    p = how.prefix(n)
    value = (held.astype(U) << U(61)) | (s >> U(3))
    often = _member(s, hot)
    if often.any():
        value[often] = (U(7) << U(61)) | (U(len(hot)) - rank[np.searchsorted(hot, s[often])].astype(U))  # the most frequent last
    cold = np.sort(np.partition(value, min(p, n - 1))[: p + 1])
    out = []
    with np.errstate(over="ignore"):
        if n <= light and len(cold) > 1:
            i, j = np.triu_indices(len(cold), 1)
            out.append(wh.mix(cold[i] * U(3) + wh.mix(cold[j])))
        if n > light or 100 * n >= how.percent * (light + 1) or len(cold) < 2:
            out.append(wh.mix(cold[:p] ^ U(0xA5A5A5A5A5A5A5A5)))
    return np.concatenate(out).view(np.int64)


def filed(docs: DataFrame, known: tuple[np.ndarray, np.ndarray, int], how: Join) -> DataFrame:
    """key, node: what each set is filed under. Copies in one task are filed once, as long as its nodes are few to remember."""
    hot_by_count, frequent, light = known
    order = np.argsort(hot_by_count)
    hot, rank = hot_by_count[order], order

    def run(batches):
        told: set[int] = set()
        for batch in batches:
            for part in wh.pieces(batch, "text", 1 << 20):
                keys, owner = [], []
                for s, held in shingle_sets(part.column("text"), how.words, frequent):
                    if not len(s) or (node := _digest(s)) in told:
                        continue
                    told.add(node)
                    keys.append(_keys(s, held, hot, rank, light, how))
                    owner.append(np.full(len(keys[-1]), node, np.int64))
                if len(told) > 1_000_000:
                    told.clear()
                if keys:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys)), pa.array(np.concatenate(owner))], ["key", "node"])

    return docs.select(F.col("text").cast("string").alias("text")).mapInArrow(run, "key long, node long")


def shared_lists(entries: DataFrame) -> DataFrame:
    """key, node, members of the keys that two sets or more are filed under. One exchange, of whole numbers."""
    same = Window.partitionBy("key")
    seen = entries.repartition("key").select("key", "node", F.count("*").over(same).alias("members"), F.min("node").over(same).alias("low"), F.max("node").over(same).alias("high"))
    return seen.where("low < high").groupBy("key", "node").agg(F.max("members").alias("members"))  # entries of copies in several tasks are one


@dataclass
class _Rows:
    """Rows of whole lists, in order of list. left: to be compared with the others; right: to be compared to."""

    group: np.ndarray
    node: np.ndarray
    n: np.ndarray
    root: np.ndarray
    home: np.ndarray
    left: np.ndarray
    right: np.ndarray
    sketch: np.ndarray


def _whole_lists(batches, rows: int = 20_000):
    """Rows of the batches, cut where a list ends."""
    held, count = [], 0

    def take(table, last):
        group = table.column("list").to_numpy()
        open_ = 0 if last else int(group[-1])
        end = len(group) if last else len(group) - int((group == open_).sum())
        return table.slice(0, end), table.slice(end)

    for batch in batches:
        held.append(pa.Table.from_batches([batch]))
        count += batch.num_rows
        if count >= rows:
            done, rest = take(pa.concat_tables(held).combine_chunks(), False)
            if done.num_rows:
                yield done
            held, count = [rest], rest.num_rows
    if held:
        done, _ = take(pa.concat_tables(held).combine_chunks(), True)
        if done.num_rows:
            yield done


def _rows(table: pa.Table) -> _Rows:
    col = lambda c: table.column(c).to_numpy()
    sketch = np.frombuffer(b"".join(table.column("sketch").to_pylist()), np.uint8).reshape(-1, BINS).astype(np.int32)
    change = np.r_[True, col("list")[1:] != col("list")[:-1]]
    return _Rows(np.cumsum(change) - 1, col("node"), col("n"), col("root"), col("home"), col("is_left"), col("is_right"), sketch)


def _near_enough(x: _Rows, i: np.ndarray, j: np.ndarray, how: Join) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The pairs of rows that may be alike, and how far apart their sketches are."""
    fits = (x.root[i] != x.root[j]) & (100 * np.minimum(x.n[i], x.n[j]) >= how.percent * np.maximum(x.n[i], x.n[j]))
    i, j = i[fits], j[fits]
    apart = np.zeros(len(i), np.int64)
    for at in range(0, len(i), 16384):
        apart[at : at + 16384] = np.abs(x.sketch[i[at : at + 16384]] - x.sketch[j[at : at + 16384]]).sum(1)
    ok = apart * (100 + how.percent) <= (x.n[i] + x.n[j]) * (100 - how.percent)
    return i[ok], j[ok], apart[ok]


def _few(batches, how: Join):
    """For each row its nearest neighbours within a few places, and the middle of its list."""
    for table in _whole_lists(batches):
        x = _rows(table)
        size, groups = len(x.node), int(x.group[-1]) + 1
        i, j = [], []
        for o in range(1, how.neighbours + 1):
            k = np.flatnonzero(x.group[o:] == x.group[:-o])
            i.append(k + o)
            j.append(k)
        a, b, apart = _near_enough(x, np.concatenate(i), np.concatenate(j), how)
        order = np.lexsort((b, apart, a))
        a, b = a[order], b[order]
        place = np.arange(len(a)) - np.searchsorted(a, a)
        a, b, apart = a[place < 2], b[place < 2], apart[order][place < 2]
        head = np.flatnonzero(np.r_[True, x.group[1:] != x.group[:-1]])
        mean = np.add.reduceat(x.sketch, head) // np.diff(np.append(head, size))[:, None]
        off = np.abs(x.sketch - mean[x.group]).sum(1)
        order = np.lexsort((x.node, off, ~x.home, x.group))
        middle = order[np.searchsorted(x.group[order], np.arange(groups))]
        c, d, far = _near_enough(x, np.arange(size), middle[x.group], how)
        yield pa.RecordBatch.from_arrays([pa.array(x.node[np.concatenate([a, c])]), pa.array(x.node[np.concatenate([b, d])]), pa.array(np.concatenate([apart, far]))], ["a", "b", "apart"])


def _all(batches, how: Join):
    """All pairs of a left and a right row of one list in different components. Pairs told before in the task are
    left out as long as there are few to remember; beyond that they may come again."""
    told: set[tuple[int, int]] = set()
    for table in _whole_lists(batches):
        x = _rows(table)
        head = np.flatnonzero(np.r_[True, x.group[1:] != x.group[:-1], True])
        lists = [(np.flatnonzero(x.left[s:e]) + s, np.flatnonzero(x.right[s:e]) + s) for s, e in zip(head[:-1].tolist(), head[1:].tolist(), strict=True)]
        i, j, count = [], [], 0

        def flush():
            a, b, _ = _near_enough(x, np.concatenate(i), np.concatenate(j), how)
            a, b = x.node[a], x.node[b]
            pairs = np.unique(np.stack([np.minimum(a, b), np.maximum(a, b)]), axis=1)
            new = [p for p in zip(*pairs.tolist(), strict=True) if p not in told]
            if len(told) + len(new) > 200_000:
                told.clear()
            told.update(new)
            return pa.RecordBatch.from_arrays([pa.array([p[0] for p in new], pa.int64()), pa.array([p[1] for p in new], pa.int64())], ["a", "b"])

        for left, right in lists:
            step = max(1, 400_000 // max(1, len(right)))
            for at in range(0, len(left), step):
                part = left[at : at + step]
                p, q = np.repeat(part, len(right)), np.tile(right, len(part))
                once = x.home[q] | (x.node[p] < x.node[q])
                i.append(p[once])
                j.append(q[once])
                count += len(i[-1])
                if count >= 400_000:
                    yield flush()
                    i, j, count = [], [], 0
        if count:
            yield flush()


def _like(key, left: pa.Table, right: pa.Table, how: Join) -> pa.Table:
    """The pairs of one task that are alike. left: node, tokens; right: a, b."""
    sets = {k: np.frombuffer(t.as_buffer(), U) for k, t in zip(left.column("node").to_pylist(), left.column("tokens"), strict=True)}
    out = []
    for a, b in zip(right.column("a").to_pylist(), right.column("b").to_pylist(), strict=True):
        x, y = sets[a], sets[b]
        at = np.searchsorted(x, y)
        at[at == len(x)] = 0
        both = int((x[at] == y).sum())
        if 100 * both >= how.percent * (len(x) + len(y) - both):
            out.append((a, b))
    return pa.table({"a": pa.array([p[0] for p in out], pa.int64()), "b": pa.array([p[1] for p in out], pa.int64())})


def _possible(pairs: DataFrame, nodes: DataFrame, how: Join) -> DataFrame:
    """The pairs that wide sketches, a thirtieth of the tokens, can't tell apart."""
    side = lambda c: nodes.select(F.col("node").alias(c), F.col("n").alias(f"n_{c}"), F.col("wide").alias(f"w_{c}"))
    both = pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "n_a", "n_b", "w_a", "w_b")

    def run(batches):
        for batch in batches:
            a, b, n, m, x, y = batch.columns
            apart = np.array([_apart(p, q) for p, q in zip(x.to_pylist(), y.to_pylist(), strict=True)], np.int64)
            ok = pa.array(apart * (100 + how.percent) <= (n.to_numpy() + m.to_numpy()) * (100 - how.percent))
            yield pa.RecordBatch.from_arrays([a.filter(ok), b.filter(ok)], ["a", "b"])

    return both.mapInArrow(run, "a long, b long")


def _dealt(pairs: DataFrame, nodes: DataFrame, how: Join) -> DataFrame:
    """pairs with the task that compares them. Pairs that hang together share a task, so that a set of tokens travels
    once; groups of more than task_bytes are dealt in blocks by blocks of their sets."""
    group = components(pairs).join(nodes.select("node", F.expr("8 * n").alias("bytes")), "node")
    size = group.groupBy("root").agg(F.sum("bytes").alias("bytes"))
    tasks = 1 + (size.agg(F.sum("bytes")).first()[0] or 0) // how.task_bytes
    size = size.select("root", F.expr(f"1 + bytes div {how.task_bytes}").alias("blocks"))
    place = group.join(size, "root").select("node", "root", "blocks", F.expr("pmod(xxhash64(node), blocks)").alias("block"))
    side = lambda c: place.select(F.col("node").alias(c), *[F.col(x).alias(f"{x}_{c}") for x in ("root", "blocks", "block")])
    both = pairs.join(side("a"), "a").join(side("b").select("b", "block_b"), "b")
    block = F.xxhash64("root_a", F.least("block_a", "block_b"), F.greatest("block_a", "block_b"))
    return both.select("a", "b", F.when(F.col("blocks_a") > 1, block).otherwise(F.pmod(F.xxhash64("root_a"), F.lit(tasks))).alias("task"))


def verify(pairs: DataFrame, nodes: DataFrame, docs: DataFrame, how: Join) -> DataFrame:
    """The pairs a, b whose sets are alike."""
    pairs = pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    pairs = cut(_possible(pairs, nodes, how), how.batch_rows)
    dealt = cut(_dealt(pairs, nodes, how))
    wanted = dealt.select("task", F.explode(F.array("a", "b")).alias("node")).distinct().join(nodes.select("node", "mark"), "node")
    wanted = cut(wanted.select("mark", F.col("node").alias("want"), "task"))
    ids = F.broadcast(wanted) if wanted.count() <= how.broadcast_ids else wanted  # else the texts are dealt by mark

    def run(batches):
        told: set[tuple[int, int]] = set()
        for batch in batches:
            for part in wh.pieces(batch, "text", 2 << 20):
                rows = []
                for task, want, s in zip(part.column("task").to_pylist(), part.column("want").to_pylist(), shingle_sets(part.column("text"), how.words), strict=True):
                    if (task, want) not in told and _digest(s) == want:
                        told.add((task, want))
                        rows.append((task, want, s.tobytes()))
                if len(told) > 1_000_000:
                    told.clear()
                yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int64()), pa.array([r[2] for r in rows], pa.binary())], ["task", "node", "tokens"])

    tokens = _texts(docs).join(ids, "mark").select("text", "want", "task").mapInArrow(run, "task long, node long, tokens binary")
    alike = tokens.groupBy("task").cogroup(dealt.groupBy("task")).applyInArrow(lambda key, x, y: _like(key, x, y, how), "a long, b long")
    alike = cut(alike, how.batch_rows)
    release(pairs, dealt, wanted)
    return alike


def classes(docs: DataFrame, how: Join = Join()) -> DataFrame:
    """doc_id, n_shingles, component_id: one row per input row.

    component_id is the smallest doc_id that links reach. Null or empty text has no
    shingles and links with nothing. Rows without doc_id take part in links, and
    have a null component_id if no row of their component has one. Repeated rows are
    copies of each other. An empty table gives no rows.
    """
    docs = docs.select("doc_id", "text")
    surveyed = cut(survey(docs, how), how.batch_rows)
    return _label(docs, surveyed, how)


def _star(part: DataFrame) -> DataFrame:
    return part.select(F.col("node").alias("a"), F.col("root").alias("b"))


def _placed(lists: DataFrame, part: DataFrame | None) -> DataFrame:
    """key, node, members, root, home (the row is in the list's largest component); lists of one component are left out."""
    if part is None:
        return lists.select("key", "node", "members", F.col("node").alias("root"), F.lit(False).alias("home"))
    own = lists.join(part, "node", "left").select("key", "node", "members", F.coalesce("root", "node").alias("root"))
    home = own.groupBy("key", "root").agg(F.count("*").alias("c"), F.min("node").alias("least")).groupBy("key").agg(F.max_by("root", F.struct("c", "root")).alias("home"), F.min("least").alias("least"), F.sum("c").alias("rows"), F.count("*").alias("parts")).where("parts > 1")
    return own.join(home, "key").select("key", "node", "members", "root", "least", (F.col("root") == F.col("home")).alias("home"))


_COLUMNS = ("list", "node", "n", "root", "home", "is_left", "is_right", "sketch")


def _scan(rows: DataFrame, nodes: DataFrame, order: list, by: str = "list") -> DataFrame:
    full = rows.join(nodes.select("node", "n", "sketch"), "node")
    tasks = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))  # named, so that few bytes don't end in few tasks: comparing takes time
    return full.repartition(tasks, by).sortWithinPartitions(*dict.fromkeys((by, "list")), *order).select(*_COLUMNS)


def _few_pairs(lists: DataFrame, nodes: DataFrame, part: DataFrame | None, how: Join, turn: int) -> DataFrame:
    run = F.xxhash64("key", F.pmod("node", F.expr(f"1 + members div {how.list_run}")))  # long lists in several runs
    # the longest lists of each set (a set is in as many as it has keys): these rounds only save work for the last
    most = lists.groupBy("node").agg(F.slice(F.sort_array(F.collect_list(F.struct("members", "key")), False), 1, how.few_lists).alias("x")).select("node", F.inline("x"))
    rows = _placed(most, part).select(run.alias("list"), "node", "root", "home", F.lit(True).alias("is_left"), F.lit(True).alias("is_right"))
    return _scan(rows, nodes, ["n", F.xxhash64(F.lit(turn), "node")]).mapInArrow(lambda it: _few(it, how), "a long, b long, apart long")


def _open_pairs(lists: DataFrame, nodes: DataFrame, part: DataFrame, how: Join) -> DataFrame:
    """Pairs of one list in different components that their sketches allow. Lists longer than list_run are cut into blocks, and every block of left rows meets every block of right ones."""
    placed = _placed(lists, part)
    # lists with the same least node, at most as many as it has keys, go to one task, where pairs that several hold are one; more rows than that to several
    spread = placed.groupBy("least").agg(F.expr(f"1 + count(*) div {how.anchor_rows}").alias("parts"))
    placed = placed.join(spread, "least").withColumn("anchor", F.xxhash64("least", F.expr("pmod(xxhash64(key), parts)"))).withColumn("blocks", F.expr(f"1 + members div {how.list_run}")).withColumn("own", F.expr("pmod(xxhash64(node), blocks)"))
    alone = placed.where("blocks = 1").select(F.xxhash64("key").alias("list"), "anchor", "node", "root", "home", (~F.col("home")).alias("is_left"), F.lit(True).alias("is_right"))
    long = placed.where("blocks > 1").select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("other"))
    left = long.where("NOT home").select(F.xxhash64("key", "own", "other").alias("list"), F.xxhash64("key", "own", "other").alias("anchor"), "node", "root", "home", F.lit(True).alias("is_left"), F.lit(False).alias("is_right"))
    right = long.select(F.xxhash64("key", "other", "own").alias("list"), F.xxhash64("key", "other", "own").alias("anchor"), "node", "root", "home", F.lit(False).alias("is_left"), F.lit(True).alias("is_right"))
    return _scan(alone.union(left).union(right), nodes, ["node"], "anchor").mapInArrow(lambda it: _all(it, how), "a long, b long").distinct()


def _label(docs: DataFrame, surveyed: DataFrame, how: Join) -> DataFrame:
    rows = surveyed.where("at is not null").select("at", "mark", "n", "node", "sketch", "wide")
    nodes = cut(rows.where("node is not null").groupBy("node").agg(F.min(F.struct("at", "mark", "n", "sketch", "wide")).alias("r")).select("node", "r.*"))
    lists = cut(shared_lists(filed(docs, habits(surveyed, how), how)), how.batch_rows)

    part = None
    for turn in range(2):
        near = _few_pairs(lists, nodes, part, how, turn)
        best = near.groupBy("a").agg(F.slice(F.array_sort(F.collect_set(F.struct("apart", "b"))), 1, 3).alias("best"))  # of at most three a key
        links = verify(best.select("a", F.explode("best.b").alias("b")), nodes, docs, how)
        before, part = part, cut(components(links if part is None else _star(part).union(links)))
        release(links, *[before] * (before is not None))
    links = verify(_open_pairs(lists, nodes, part, how), nodes, docs, how)
    whole = cut(components(_star(part).union(links)))
    release(links, part, lists)

    known = nodes.select("node", "at").join(whole, "node", "left").withColumn("root", F.coalesce("root", "node"))
    label = known.join(known.groupBy("root").agg(F.min("at").alias("component")), "root").select("node", "component")
    out = rows.select("at", "n", "node").join(label, "node", "left")
    real = lambda c: F.when(F.col(c) != _LAST, F.col(c))
    return out.select(real("at").alias("doc_id"), F.col("n").alias("n_shingles"), F.when(F.col("node").isNull(), real("at")).otherwise(real("component")).alias("component_id"))


def keep_one(docs: DataFrame, how: Join = Join()) -> DataFrame:
    """One row of each group of linked documents: that of the smallest doc_id. Columns of docs; rows without doc_id or shingles stay."""
    found = classes(docs, how).where("doc_id is not null")
    fate = found.groupBy(F.col("doc_id").alias("f_id")).agg(F.max(F.col("component_id") < F.col("doc_id")).alias("gone"), (F.count("*") > 1).alias("again"))
    fate = cut(fate.where("gone or again").withColumn("gone", F.coalesce("gone", F.lit(False))))
    lost, again = fate.agg(F.count_if("gone"), F.count_if(F.expr("again AND NOT gone"))).first()
    small = lambda df, n: F.broadcast(df) if n <= how.broadcast_ids else df
    rows = docs.select(F.struct("*").alias("doc"), F.col("doc_id").cast("long").alias("f_id"))
    rows = rows.join(small(fate.where("gone").select("f_id"), lost), "f_id", "left_anti")
    if not again:  # as a rule ids are unique
        return rows.select("doc.*")
    twice = small(fate.where("again AND NOT gone").select("f_id"), again)
    once = rows.join(twice, "f_id", "left_anti").select("doc")
    return once.union(rows.join(twice, "f_id", "left_semi").withColumn("r_text", F.xxhash64("doc.text")).dropDuplicates(["f_id", "r_text"]).select("doc")).select("doc.*")
