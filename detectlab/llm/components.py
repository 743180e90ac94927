"""Connected components of an edge table by alternating star contraction.

Every round is two aggregations and two joins; edges are first contracted within
each Arrow batch by union-find, which shortens chains. A table of few edges, by count,
is solved by union-find in one task instead, with the same result. Nothing but counts
and one checksum a round reaches the driver.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from detectlab.llm.frames import cut, release


def _contract(batches):
    for batch in batches:
        a, b = (batch.column(k).to_numpy() for k in range(2))
        nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
        root = np.arange(len(nodes))

        def find(x):
            while root[x] != x:
                root[x] = root[root[x]]
                x = root[x]
            return x

        n = len(a)
        for x, y in zip(at[:n].tolist(), at[n:].tolist(), strict=True):
            x, y = find(x), find(y)
            if x != y:
                root[max(x, y)] = min(x, y)
        own = np.array([find(x) for x in range(len(nodes))], np.int64)
        far = np.flatnonzero(own != np.arange(len(nodes)))
        yield pa.RecordBatch.from_arrays([pa.array(nodes[far]), pa.array(nodes[own[far]])], ["u", "v"])


def _solve(batches):
    held = [pa.Table.from_batches([b]) for b in batches]
    if held:
        whole = pa.concat_tables(held).combine_chunks()
        if whole.num_rows:
            yield from _contract(whole.to_batches())


def components(edges: DataFrame, rounds: int = 60, small: int = 1_000_000) -> DataFrame:
    """node, root (the smallest node it reaches) for every node with an edge. edges: two long columns; nulls and loops are ignored.
    small: edges up to which one task solves all (16 bytes each)."""
    a, b = edges.columns
    e = edges.select(F.col(a).cast("long").alias("u"), F.col(b).cast("long").alias("v")).where("u is not null and v is not null and u <> v")
    e = cut(e.mapInArrow(_contract, "u long, v long").distinct())
    seen = None
    if e.count() <= small:
        few, rounds = cut(e.repartition(1).mapInArrow(_solve, "u long, v long")), 0
        release(e)
        e = few
    for _ in range(rounds):
        both = e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        down = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(down, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")
        before, e = e, cut(small.union(down.select("u", F.col("m").alias("v"))).distinct())
        release(before)
        now = tuple(e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if now == seen:
            break
        seen = now
    else:
        if rounds:
            raise RuntimeError(f"components not stable after {rounds} rounds")
    return e.select(F.col("u").alias("node"), F.col("v").alias("root")).union(e.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
