"""Connected components of a link graph, by alternating star contraction on DataFrames."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fewbit.llm._store import Stored

_CHUNK = 1_000_000


def spanning_forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, smallest node it is tied to) for every node that isn't itself the smallest of its group."""
    nodes, ends = np.unique(np.concatenate([a, b]), return_inverse=True)
    up = list(range(len(nodes)))
    half = len(a)

    def root(x: int) -> int:
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    for x, y in zip(ends[:half].tolist(), ends[half:].tolist(), strict=True):
        x, y = root(x), root(y)
        if x != y:
            up[max(x, y)] = min(x, y)
    top = np.fromiter((root(x) for x in range(len(nodes))), np.int64, len(nodes))
    moved = top != np.arange(len(nodes))
    return nodes[moved], nodes[top[moved]]


def _contract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    kept_a, kept_b, held = [], [], 0

    def flush():
        u, v = spanning_forest(np.concatenate(kept_a), np.concatenate(kept_b))
        return pa.RecordBatch.from_arrays([pa.array(u), pa.array(v)], ["u", "v"])

    for batch in batches:
        kept_a.append(batch.column(0).to_numpy(zero_copy_only=False))
        kept_b.append(batch.column(1).to_numpy(zero_copy_only=False))
        held += batch.num_rows
        if held >= _CHUNK:
            yield flush()
            kept_a, kept_b, held = [], [], 0
    if held:
        yield flush()


def _mark(edges: DataFrame) -> tuple[int, int]:
    row = edges.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("u", "v").cast("decimal(20,0)")), F.lit(0))).first()
    return int(row[0]), int(row[1])


#: Nodes with more edges than 1 in HUBS of all are joined by broadcast, so there are 2 * HUBS of them at most; none with fewer edges than LEAST is.
HUBS, LEAST = 100_000, 256


def _beside_least(edges: DataFrame, count: int) -> DataFrame:
    """edges (u, v) with m, the least v of their u. The edges of a hub stay in the tasks they are in; the others meet by u."""
    low = edges.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("c"))
    limit = max(LEAST, 2 * count // HUBS)
    hubs = F.broadcast(low.where(F.col("c") > limit).select("u", F.col("m").alias("hub")))
    known = edges.join(hubs, "u", "left")
    rest = known.where("hub IS NULL").select("u", "v").join(low.where(F.col("c") <= limit).select("u", "m"), "u")
    return known.where("hub IS NOT NULL").select("u", "v", F.col("hub").alias("m")).unionByName(rest)


def components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node long, component long) of every linked node; component is its smallest reachable node.

    links: two long columns in any order and number; loops and repeats are harmless, nulls are skipped; no links give an
    empty table. Each round does a large-star and a small-star step, so the number of rounds grows with the logarithm of
    the longest chain. A round's edges are written to the shared folder, and no task or driver holds a component; the
    result is the last round's table there.
    """
    edges = links.select(F.col(a).cast("long").alias("u"), F.col(b).cast("long").alias("v")).where("u <> v")
    kept = Stored(edges.mapInArrow(_contract, "u long, v long").distinct())
    mark = _mark(kept.df)
    while mark[0]:
        e = kept.df
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = _beside_least(both, 2 * mark[0]).select("u", "v", F.least("u", "m").alias("m"))
        large = Stored(low.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct())
        small = _beside_least(large.df, mark[0]).select(
            F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")
        )
        after = Stored(small.select("e.u", "e.v").where("u <> v").distinct())
        now = _mark(after.df)
        kept.drop()
        large.drop()
        kept = after
        if now == mark:
            break
        mark = now
    return kept.df.select(F.col("u").alias("node"), F.col("v").alias("component"))
