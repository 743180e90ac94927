"""A whole project: context, tool rounds, traces, and the score against fixes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from detectlab.functions import simulate
from detectlab.sources.tables import KINDS, cut, shared_folder, stored

#: Classes that count as one. Fixed values.
MERGE = {"CWE-125": "CWE-119", "CWE-787": "CWE-119", "CWE-415": "CWE-416"}
#: Classes in scope at project level. Fixed values.
SCOPE = {
    "c": ("CWE-125", "CWE-787", "CWE-119", "CWE-416", "CWE-415", "CWE-476", "CWE-190"),
    "java": ("CWE-74", "CWE-22", "CWE-918", "CWE-502", "CWE-917", "CWE-90", "CWE-154", "CWE-470", "CWE-777", "CWE-89", "CWE-643", "CWE-611", "CWE-835"),
}


def merge_classes(c: str | Column, mapping: dict[str, str] | None = None) -> Column:
    c = F.col(c) if isinstance(c, str) else c
    table = F.create_map(*[F.lit(x) for kv in (mapping or MERGE).items() for x in kv])
    return F.coalesce(F.try_element_at(table, c), c)


def in_scope(df: DataFrame, codes: tuple[str, ...], column: str = "cwe") -> DataFrame:
    return df.where(F.col(column).isin(*codes))


def initial_context(paths: DataFrame, bodies: DataFrame, budget: int) -> DataFrame:
    """entry, target, functions, chars, context: bodies of all nodes on the pair's paths, each once, nearest the target first, while they fit the budget in characters."""
    nodes = paths.select("entry", "target", F.posexplode("path").alias("i", "node"), F.size("path").alias("m"))
    nodes = nodes.groupBy("entry", "target", "node").agg(F.min(F.col("m") - F.col("i")).alias("far"))
    rows = nodes.join(bodies.select("node", F.length("code").alias("size")), "node")
    w = Window.partitionBy("entry", "target").orderBy("far", "node").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rows = rows.withColumn("upto", F.sum("size").over(w)).where(F.col("upto") <= budget).join(bodies, "node")  # texts of what fits alone
    x = F.array_sort(F.collect_list(F.struct("far", "node", "code")))
    return rows.groupBy("entry", "target").agg(F.count("*").alias("functions"), F.max("upto").alias("chars"), x.alias("x")).withColumn("context", F.array_join(F.transform("x", lambda r: r.code), "\n")).drop("x")


#: Paths that are packed at once, of a task, and of a part of a task; the number of texts without one.
PACK_ROWS, TASK_PATHS, PART_PATHS, NO_NUMBER = 500_000, 6_000_000, 400_000, -(2**63)


def context_digests(paths: DataFrame, docs: DataFrame, budget: int, about: int, k: int = 3, seed: int = 1) -> DataFrame:
    """entry, target, functions, chars, context_md5: the digest of what initial_context makes of k paths a pair, as graph.sample_paths takes them.

    paths (target, tail): all paths, by codes of nodes, tail from the end; about: how many. A node's body is the document
    numbered as its key, modulo their count. Texts are written once to the shared folder. Paths go to tasks by target, packed
    by column, with the texts' places; there pairs are sampled, filled up to the budget and hashed, parts of the targets in turn.
    """
    tasks = max(1, min(docs.sparkSession.sparkContext.defaultParallelism, -(-about // 50_000)), -(-about // TASK_PATHS))
    parts = max(1, -(-about // (tasks * PART_PATHS)))
    packed = paths.mapInArrow(lambda batches: _packed(batches, tasks, parts), "task int, part int, width long, size long, data binary")
    folder = shared_folder(docs.sparkSession)
    texts = docs.select(F.col("doc_id").cast("long").alias("id"), F.length("text").alias("size"), F.col("text").cast("binary").alias("text"))
    files = stored(texts.mapInArrow(lambda batches: _written(batches, folder), "file string, rows long, places binary"))
    n = files.agg(F.coalesce(F.sum("rows"), F.lit(0))).first()[0]
    every = files.where("rows > 0").select(F.explode(F.sequence(F.lit(0), F.lit(tasks - 1))).alias("task"), F.lit(-1).alias("part"), F.lit(None).cast("long").alias("width"), F.col("rows").alias("size"), F.col("places").alias("data"), "file")
    met = every.union(packed.withColumn("file", F.lit(None).cast("string"))).repartitionById(tasks, F.col("task")).sortWithinPartitions("task", "part")
    out = "entry string, target string, functions long, chars long, context_md5 string"
    return met.mapInArrow(lambda batches: _contexts(batches, n, budget, k, seed), out)


def _written(batches, folder: str):
    """Writes texts to a file of its own, each after a line's end; places: number, size, if null, start and end of each, by column."""
    import uuid

    import numpy as np
    import pyarrow as pa

    from detectlab.sources.shared import opened

    file, end, places = f"{folder}/texts-{uuid.uuid4().hex}", 0, []
    with opened(file, "wb") as out:
        for batch in batches:
            for number, size, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                start = end
                if text.is_valid:
                    out.write(b"\n")
                    out.write(text.as_buffer())
                    end += 1 + text.as_buffer().size
                places.append((NO_NUMBER if number is None else number, size or 0, size is None, start, end))
    data = pa.compress(np.array(places, "i8").reshape(-1, 5).T.tobytes(), codec="zstd", asbytes=True)
    yield pa.RecordBatch.from_arrays([pa.array([file]), pa.array([len(places)], pa.int64()), pa.array([data], pa.binary())], ["file", "rows", "places"])


def _packed(batches, tasks: int, parts: int):
    """Blocks of paths of one length and part: the columns target and tail, sorted, by bytes of the same weight."""
    import numpy as np
    import pyarrow as pa

    def blocks(held):
        for width in sorted(held):
            rows = np.concatenate(held[width])
            where = ((rows[:, 0] >> 3).astype("u8") * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(33)).astype("i8") % (tasks * parts)
            order = np.lexsort((rows[:, 1], rows[:, 0], where))
            rows, where = rows[order], where[order]
            cuts = np.flatnonzero(np.diff(where, prepend=-1))
            for a, b in zip(cuts, [*cuts[1:], len(rows)], strict=True):
                x = rows[a:b].copy()
                x[1:, 0] -= rows[a : b - 1, 0]
                data = pa.compress(np.ascontiguousarray(x.T).view("u1").reshape(width, b - a, 8).transpose(0, 2, 1).tobytes(), codec="zstd", asbytes=True)
                yield int(where[a]) % tasks, int(where[a]) // tasks, width, int(b - a), data

    def sent(held):
        rows = list(blocks(held))
        types = (pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.binary())
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], ["task", "part", "width", "size", "data"])

    held, count = {}, 0
    for batch in batches:
        target, tails = batch.column(0).to_numpy(zero_copy_only=False), batch.column(1)
        flat, ends = tails.flatten().to_numpy(zero_copy_only=False), np.cumsum(tails.value_lengths().to_numpy(zero_copy_only=False))
        lengths = np.diff(ends, prepend=0)
        for m in np.unique(lengths):
            which = np.flatnonzero(lengths == m)
            at = (ends[which] - m)[:, None] + np.arange(m)
            held.setdefault(int(m) + 1, []).append(np.column_stack([target[which], flat[at]]))
        count += len(target)
        if count >= PACK_ROWS:
            yield sent(held)
            held, count = {}, 0
    if count:
        yield sent(held)


def _by_name(codes):
    """Numbers in the order of the nodes' names."""
    import numpy as np

    key, kind = codes >> 3, codes & 7
    size = np.abs(key)
    if len(codes) and size.max() >= 10**15:
        each, at = np.unique(codes, return_inverse=True)
        names = [_name(c) for c in each.tolist()]
        place = np.empty(len(each), "i8")
        place[sorted(range(len(each)), key=names.__getitem__)] = np.arange(len(each))
        return place[at]
    tens = 10 ** np.arange(16, dtype="i8")
    digits = np.maximum(np.searchsorted(tens, size, "right"), 1)
    letter = np.argsort(np.argsort(list(KINDS)))
    letter = np.append(letter, [0] * (8 - len(letter)))[kind]
    return ((letter * 2 + (key >= 0)) * 10**15 + size * tens[15 - digits]) * 16 + digits


def _name(node: int) -> str:
    return f"{KINDS[node & 7]}{node >> 3}"


def _picked(rows, k: int, seed: int):
    """Pairs (entry, target) and, for each row picked, its pair. rows: columns length, target and tail; repeats go."""
    import numpy as np

    length, target = rows[:, 0], rows[:, 1]
    entry = rows[np.arange(len(rows)), length + 1]
    names = [np.where(length >= j, _by_name(rows[:, j + 1]), -1) for j in range(1, rows.shape[1] - 1)]
    order = np.lexsort((*names[::-1], length, entry, target))
    rows, entry = rows[order], entry[order]
    fresh = np.append(True, (rows[1:] != rows[:-1]).any(axis=1))
    rows, entry = rows[fresh], entry[fresh]
    first = np.flatnonzero(np.append(True, (rows[1:, 1] != rows[:-1, 1]) | (entry[1:] != entry[:-1])))
    n = np.diff(np.append(first, len(rows)))
    pairs = np.column_stack([entry[first], rows[first, 1]])
    keys = pairs >> 3
    if len(keys) and np.abs(keys).max() >= 10**14:  # products would leave 64 bits
        keys = np.fmod(keys, 2147483647)
    start = np.fmod(keys[:, 0] * 48271 + keys[:, 1] * 16807 + seed * 69621 + 12345, 2147483647)
    which, at = [], []
    for i in range(k):
        r = np.where(n <= k, i, np.fmod(start + i * (n // k), n))
        there = np.flatnonzero((i < n) & (r >= 0))
        which.append(there)
        at.append(first[there] + r[there])
    return pairs, np.concatenate(which), rows[np.concatenate(at)]


def _contexts(batches, n: int, budget: int, k: int, seed: int):
    import numpy as np
    import pyarrow as pa

    def part(held, texts):
        if not texts.ids.size:
            return
        wide = max(x.shape[1] for x in held)
        rows = np.concatenate([np.pad(x, ((0, 0), (0, wide - x.shape[1])), constant_values=-1) for x in held])
        pairs, pair, picked = _picked(rows, k, seed)
        # nodes of each pair, once, at their least distance from the target
        i, j = np.nonzero(np.arange(wide - 1)[None, :] <= picked[:, :1])
        pair, far, node = pair[i], j + 1, picked[i, j + 1]
        order = np.lexsort((far, node, pair))
        pair, far, node = pair[order], far[order], node[order]
        once = np.append(True, (pair[1:] != pair[:-1]) | (node[1:] != node[:-1]))
        pair, far, node = pair[once], far[once], node[once]
        order = np.lexsort((_by_name(node), far, pair))
        pair, doc = pair[order], np.fmod(node[order] >> 3, n)
        at = np.minimum(np.searchsorted(texts.ids, doc), len(texts.ids) - 1)
        known = texts.ids[at] == doc
        pair, at = pair[known], at[known]
        size, some = texts.sizes[at], ~texts.null[at]
        # running sums of a pair
        first = np.flatnonzero(np.append(True, pair[1:] != pair[:-1])) if len(pair) else np.empty(0, "i8")
        own = np.repeat(np.arange(len(first)), np.diff(np.append(first, len(pair))))
        since = lambda x: (c := np.cumsum(x)) - (c - x)[first][own]
        upto = since(size)
        kept = (upto <= budget) & (since(some.astype("i8")) > 0)
        pair, at, upto = pair[kept], at[kept], upto[kept]
        if not len(pair):
            return
        first = np.flatnonzero(np.append(True, pair[1:] != pair[:-1]))
        ends = np.append(first[1:], len(pair))
        digests = texts.digests(at, first.tolist(), ends.tolist())
        entry, target = pairs[pair[first]].T
        columns = [[_name(x) for x in entry.tolist()], [_name(x) for x in target.tolist()], ends - first, upto[ends - 1], digests]
        out = pa.RecordBatch.from_arrays([pa.array(c) for c in columns], ["entry", "target", "functions", "chars", "context_md5"])
        for a in range(0, len(first), 10_000):
            yield out.slice(a, 10_000)

    texts, held, now = _Texts(), [], None
    for batch in batches:
        for p, width, size, data, file in zip(*[batch.column(i).to_pylist() for i in (1, 2, 3)], batch.column(4), batch.column(5).to_pylist(), strict=True):
            if p < 0:
                texts.add(file, np.frombuffer(pa.decompress(data.as_buffer(), size * 40, codec="zstd"), "i8").reshape(5, size))
                continue
            if p != now and held:
                yield from part(held, texts.ready())
                held = []
            now = p
            raw = np.frombuffer(pa.decompress(data.as_buffer(), width * size * 8, codec="zstd"), "u1")
            x = raw.reshape(width, 8, size).transpose(0, 2, 1).copy().view("i8").reshape(width, size).T
            held.append(np.column_stack([np.full(size, width - 1), np.cumsum(x[:, 0]), x[:, 1:]]))
    if held:
        yield from part(held, texts.ready())


class _Texts:
    """Texts by number, read where they lie in their files."""

    def __init__(self):
        self.files, self.places, self.ids = [], [], None

    def add(self, file: str, places) -> None:
        self.places.append((len(self.files), places))
        self.files.append(file)

    def ready(self) -> _Texts:
        import numpy as np

        from detectlab.sources.shared import mapped

        if self.ids is None:
            x = np.concatenate([np.empty((6, 0), "i8"), *[np.vstack([p, np.full(p.shape[1], i)]) for i, p in self.places]], axis=1)
            x = x[:, x[0] != NO_NUMBER]
            x = x[:, np.argsort(x[0], kind="stable")]
            self.ids, self.sizes, self.null, self.places = x[0], x[1], x[2] == 1, []
            self.starts, self.ends, self.of = x[3], x[4], x[5]
            self.maps = [mapped(f) for f in self.files]
        return self

    def digests(self, at, first: list[int], ends: list[int]) -> list[str]:
        from hashlib import md5

        spans = list(zip(self.of[at].tolist(), self.starts[at].tolist(), self.ends[at].tolist(), strict=True))
        out, maps = [], self.maps
        for a, b in zip(first, ends, strict=True):
            h, skip = md5(usedforsecurity=False), 1
            for f, x, y in spans[a:b]:
                if x < y:  # null texts have no line
                    h.update(maps[f][x + skip : y])
                    skip = 0
            out.append(h.hexdigest())
        return out


def lookup(requests: DataFrame, functions: DataFrame) -> DataFrame:
    """Adds found and code to requests (name): unknown names are told as misses. Only the open requests move; functions may be bucketed by name."""
    return requests.join(functions.select(F.col("fn_id").alias("name"), "code", F.lit(True).alias("hit")), "name", "left").withColumn("found", F.coalesce("hit", F.lit(False))).drop("hit")


def asks(target_no: Column, round_: Column, functions: int) -> Column:
    """Names a simulated model asks for in a round: two functions, now and then one that doesn't exist."""
    return F.array(*[F.concat(F.lit("p"), (1 + (target_no * (7 + k) + round_ * 13 + k) % (functions + F.floor(functions / 20))).cast("string")) for k in (0, 1)])


def run_agent(targets: DataFrame, functions: DataFrame, n_functions: int, *, rounds: int = 3, skill: int = 600) -> DataFrame:
    """fn_id, round, calls, hits, answered: one row a target and round. A target answers when its draw falls under skill (thousandths) or the rounds are over.

    Each round is one join of the open requests; the state between rounds is written, so a lost executor repeats one round.
    """
    open_ = targets.select("fn_id", F.substring("fn_id", 2, 18).cast("long").alias("no"))
    trace = None
    for r in range(1, rounds + 1):
        reqs = open_.select("fn_id", "no", F.explode(asks(F.col("no"), F.lit(r), F.lit(n_functions))).alias("name"))
        got = lookup(reqs, functions).groupBy("fn_id", "no").agg(F.count("*").alias("calls"), F.sum(F.col("found").cast("int")).alias("hits"))
        draw = F.expr(simulate.draw("no", "4", str(r), 8)) % 1000
        step = cut(got.select("fn_id", "no", F.lit(r).alias("round"), "calls", "hits", ((draw < skill) | F.lit(r == rounds)).alias("answered")))
        trace = step.drop("no") if trace is None else trace.union(step.drop("no"))
        open_ = step.where("NOT answered").select("fn_id", "no")
    return trace


def simulated_flags(targets: DataFrame, patches: DataFrame, tools: dict[str, tuple[int, int, int]]) -> DataFrame:
    """project, fn_id, tool: flags of simulated tools (number, hits and false alarms in a thousand)."""
    truth = patches.select("project", "fn_id").distinct().withColumn("vuln", F.lit(True))
    rows = targets.join(truth, ["project", "fn_id"], "left").withColumn("no", F.substring("fn_id", 2, 18).cast("long"))
    table = targets.sparkSession.createDataFrame([(n, *v) for n, v in tools.items()], "tool string, t int, hit int, alarm int")
    flagged = (F.expr(simulate.draw("no", "t", "length(project)", 9)) % 1000) < F.when(F.coalesce("vuln", F.lit(False)), F.col("hit")).otherwise(F.col("alarm"))
    return rows.crossJoin(F.broadcast(table)).where(flagged).select("project", "fn_id", "tool")


#: Simulated tools: number, hits and false alarms in a thousand.
TOOLS = {"agent student": (10, 600, 60), "agent P1": (4, 640, 320), "agent P2": (5, 650, 550), "student, untrained tools": (9, 450, 120), "flow auditor": (12, 60, 20), "rules": (13, 40, 90)}


def vuln_hits(flags: DataFrame, patches: DataFrame) -> DataFrame:
    """tool, project, vuln_id, found: found if any function of its fix is flagged."""
    hit = flags.join(patches, ["project", "fn_id"]).select("tool", "project", "vuln_id").distinct().withColumn("hit", F.lit(True))
    tools = flags.select("tool").distinct()
    return patches.select("project", "vuln_id").distinct().crossJoin(F.broadcast(tools)).join(hit, ["tool", "project", "vuln_id"], "left").select("tool", "project", "vuln_id", F.coalesce("hit", F.lit(False)).alias("found"))


def false_flags(flags: DataFrame, patches: DataFrame) -> DataFrame:
    """Flags outside every fix of their project."""
    return flags.join(patches.select("project", "fn_id").distinct(), ["project", "fn_id"], "left_anti")


def project_score(flags: DataFrame, patches: DataFrame, targets: DataFrame) -> DataFrame:
    """tool, project, vulns, found, flagged, false_flags, targets."""
    v = vuln_hits(flags, patches).groupBy("tool", "project").agg(F.count("*").alias("vulns"), F.sum(F.col("found").cast("int")).alias("found"))
    n = flags.groupBy("tool", "project").agg(F.count("*").alias("flagged"))
    wrong = false_flags(flags, patches).groupBy("tool", "project").agg(F.count("*").alias("false_flags"))
    t = targets.groupBy("project").agg(F.count("*").alias("targets"))
    out = v.join(n, ["tool", "project"], "left").join(wrong, ["tool", "project"], "left").join(t, "project", "left")
    return out.select("tool", "project", "vulns", "found", *[F.coalesce(c, F.lit(0)).alias(c) for c in ("flagged", "false_flags", "targets")])


def unknown_findings(flags: DataFrame, patches: DataFrame) -> DataFrame:
    """project, fn_id, tools, rank: functions flagged outside any known fix, those most tools agree on first."""
    per = false_flags(flags, patches).groupBy("project", "fn_id").agg(F.countDistinct("tool").alias("tools"))
    return per.withColumn("rank", F.rank().over(Window.partitionBy("project").orderBy(F.desc("tools"))))


def confirm_by_fuzz(flags: DataFrame, walks: DataFrame) -> DataFrame:
    """Flags whose function some walk reaches."""
    return flags.join(walks.select(F.col("node").alias("fn_id")).distinct(), "fn_id", "left_semi")


def project_leak_check(train: DataFrame, projects: DataFrame) -> DataFrame:
    """leaked: how many rows of train belong to one of projects; both have a column project."""
    return train.join(projects.select("project"), "project", "left_semi").agg(F.count("*").alias("leaked"))
