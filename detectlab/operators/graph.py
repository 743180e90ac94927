"""Call graphs: indirect edges, reachability, path counts and sampled paths."""

from __future__ import annotations

from collections.abc import Callable
from itertools import count

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from detectlab.sources.tables import cut, stored


def signature(df: DataFrame) -> DataFrame:
    return df.withColumn("sig", F.concat_ws("|", F.col("arity").cast("string"), F.array_join("param_types", ",")))


def indirect_edges(functions: DataFrame, *, materialise: bool = False) -> DataFrame:
    """src, dst. Pointer call sites to address-taken functions of the same number and types of parameters.

    Factored, an edge goes from the site to its signature's node and from there to each function: linear in both.
    materialise forms the product of each signature: sites dealt out in the order of signatures, so that a large one is
    the work of many tasks and files repeat their names, against blocks of functions.
    """
    f = signature(functions)
    sites, taken = f.where("pointer_site").select(F.col("fn_id").alias("src"), "sig"), f.where("address_taken").select(F.col("fn_id").alias("dst"), "sig")
    if materialise:
        return _product(sites, taken)
    return sites.select("src", F.concat(F.lit("sig:"), "sig").alias("dst")).union(taken.select(F.concat(F.lit("sig:"), "sig").alias("src"), "dst"))


#: Edges of a task, functions of a block, and functions that are broadcast at most; beyond, both sides are dealt by signature and one of SALTS.
TASK_EDGES, BLOCK, TAKEN_ROWS, SALTS = 10_000_000, 1000, 1_000_000, 16


def _product(sites: DataFrame, taken: DataFrame) -> DataFrame:
    n = taken.groupBy("sig").agg(F.count("*").alias("n"))
    edges = sites.join(n, "sig").agg(F.sum("n").alias("e")).first()[0] or 0
    rows, most = n.agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.max("n"), F.lit(1))).first()
    tasks = max(int(sites.sparkSession.conf.get("spark.sql.shuffle.partitions")) if edges > TASK_EDGES else 1, -(-edges // TASK_EDGES), 1)
    block = F.pmod(F.xxhash64("dst"), F.lit(-(-most // BLOCK)))
    blocks = taken.groupBy("sig", block.alias("block")).agg(F.collect_list("dst").alias("many")).select("sig", "many")
    if rows <= TAKEN_ROWS:
        met = sites.repartitionByRange(tasks, "sig", "src").join(F.broadcast(blocks), "sig")
    else:
        met = sites.withColumn("salt", F.pmod(F.xxhash64("src"), F.lit(SALTS)).cast("int")).join(blocks.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)))), ["sig", "salt"])
    return met.select("src", F.explode("many").alias("dst")).where("src <> dst")


def signature_groups(functions: DataFrame) -> DataFrame:
    """sig, sites, takers: sizes of the groups that indirect edges come from; those with both."""
    f = signature(functions).groupBy("sig").agg(F.sum(F.col("pointer_site").cast("int")).alias("sites"), F.sum(F.col("address_taken").cast("int")).alias("takers"))
    return f.where("sites > 0 AND takers > 0")


def reachable(edges: DataFrame, entries: DataFrame) -> DataFrame:
    """node, depth: fewest edges from any entry. A frontier a round; the visited set ends cycles."""
    seen = cut(entries.select(F.col("entry").alias("node"), F.lit(0).alias("depth")))
    front = seen
    for d in count(1):
        step = front.join(edges, F.col("node") == F.col("src")).select(F.col("dst").alias("node")).distinct()
        front = cut(step.join(seen.select("node"), "node", "left_anti").withColumn("depth", F.lit(d)))
        if front.limit(1).count() == 0:
            break
        seen = cut(seen.union(front))
    return seen


def level_counts(edges: DataFrame | Callable[[DataFrame], list[DataFrame]], entries: DataFrame, max_depth: int = 16, *, layered: bool = False) -> DataFrame:
    """entry, node, d, c: how many paths of d edges lead there. Needs an acyclic graph, or layered, which keeps the edges that raise the fewest edges from the entry.

    edges: all of them, or a function that gives those out of the nodes of a level, in tables without common edges.
    """
    at = stored(entries.select("entry", F.col("entry").alias("node"), F.lit(0).alias("d"), F.lit(1).cast("decimal(38,0)").alias("c")))
    out, seen = at, at.select("entry", "node")
    for d in range(1, max_depth + 1):
        step = None
        for e in edges(at) if callable(edges) else [edges]:
            one = at.join(e, F.col("node") == F.col("src")).select("entry", F.col("dst").alias("node"), "c")
            step = one if step is None else step.union(one)
        step = step.groupBy("entry", "node").agg(F.sum("c").cast("decimal(38,0)").alias("c"))
        if layered:
            step = step.join(seen, ["entry", "node"], "left_anti")
        at = stored(step.select("entry", "node", F.lit(d).alias("d"), "c"))
        if at.limit(1).count() == 0:
            return out
        out = out.union(at)
        if layered:
            seen = stored(seen.union(at.select("entry", "node")))
    if not layered:
        raise ValueError(f"paths of {max_depth} edges and more: the graph may have a cycle; use layered=True or simple_paths")
    return out


def path_counts(levels: DataFrame, targets: DataFrame) -> DataFrame:
    """entry, target, paths, shortest."""
    t = targets.select(F.col("node"))
    return levels.join(t, "node", "left_semi").groupBy("entry", F.col("node").alias("target")).agg(F.sum("c").cast("decimal(38,0)").alias("paths"), F.min("d").alias("shortest"))


def sample_paths(edges: DataFrame, levels: DataFrame, targets: DataFrame, k: int = 3, seed: int = 1, mode: str = "uniform") -> DataFrame:
    """entry, target, n, path: k distinct paths of each pair, or all if there are no more.

    Paths are ranked by length, then by their nodes from the end. uniform: ranks a k-th of all apart from a seeded
    start; shortest: the first ranks. A path is walked back from the target by cumulative counts of the edges in,
    all pairs at once: one join and one window a level, whatever the number of paths.
    """
    levels = cut(levels)
    depth = levels.agg(F.max("d")).first()[0] or 0
    total = path_counts(levels, targets).select("entry", "target", F.col("paths").cast("long").alias("paths"))
    number = lambda c: F.substring(c, 2, 18).cast("long")
    start = (number("entry") * 48271 + number("target") * 16807 + seed * 69621 + 12345) % 2147483647
    ranks = F.sequence(F.lit(0).cast("long"), F.least(F.col("paths"), F.lit(k).cast("long")) - 1)
    if mode == "uniform":
        rank = F.when(F.col("paths") <= k, F.col("i")).otherwise((start + F.col("i") * F.expr(f"paths div {k}")) % F.col("paths"))
    elif mode == "shortest":
        rank = F.col("i")
    else:
        raise ValueError(mode)
    asked = total.withColumn("i", F.explode(ranks)).select("entry", "target", F.col("i").cast("int").alias("n"), rank.alias("r"))
    # the length first: ranks are by length
    by_len = levels.select("entry", F.col("node").alias("target"), "d", F.col("c").cast("long").alias("c"))
    w = Window.partitionBy("entry", "target").orderBy("d").rowsBetween(Window.unboundedPreceding, -1)
    by_len = by_len.withColumn("lo", F.coalesce(F.sum("c").over(w), F.lit(0)))
    open_ = asked.join(by_len, ["entry", "target"]).where("r >= lo AND r < lo + c").select("entry", "target", "n", (F.col("r") - F.col("lo")).alias("r"), "d", F.col("target").alias("node"), F.array("target").alias("path"))
    open_ = cut(open_)
    done = open_.where("d = 0")
    for _ in range(depth):
        walk = open_.where("d > 0")
        need = walk.select("entry", "node", "d").distinct()
        into = need.join(edges, F.col("node") == F.col("dst")).select("entry", "node", "d", "src")
        before = levels.select("entry", F.col("node").alias("src"), (F.col("d") + 1).alias("d"), F.col("c").cast("long").alias("c"))
        into = into.join(before, ["entry", "src", "d"])
        w = Window.partitionBy("entry", "node", "d").orderBy("src").rowsBetween(Window.unboundedPreceding, -1)
        into = into.withColumn("lo", F.coalesce(F.sum("c").over(w), F.lit(0)))
        step = walk.join(into, ["entry", "node", "d"]).where("r >= lo AND r < lo + c")
        open_ = cut(step.select("entry", "target", "n", (F.col("r") - F.col("lo")).alias("r"), (F.col("d") - 1).alias("d"), F.col("src").alias("node"), F.concat(F.array("src"), "path").alias("path")))
        done = done.union(open_.where("d = 0"))
    return done.select("entry", "target", "n", "path")


def simple_paths(edges: DataFrame, entries: DataFrame, targets: DataFrame, max_depth: int | None = None) -> DataFrame:
    """entry, target, path: all paths without a repeated node, for small cyclic graphs; of max_depth edges at most if that is asked for."""
    at = entries.select("entry", F.col("entry").alias("node"), F.array("entry").alias("path"))
    out = None
    for _ in range(max_depth) if max_depth else count():
        at = cut(at.join(edges, F.col("node") == F.col("src")).where(~F.array_contains("path", F.col("dst"))).select("entry", F.col("dst").alias("node"), F.concat("path", F.array("dst")).alias("path")))
        hit = at.join(targets, "node", "left_semi")
        out = hit if out is None else out.union(hit)
        if at.limit(1).count() == 0:
            break
    return out.select("entry", F.col("node").alias("target"), "path")
