"""Embedding near-dedup by sorted projection passes.

Each pass orders all vectors by the concatenated signs of random projections, so that close vectors tend to be
neighbours; vectors within a bounded window of that order are compared exactly. The number of passes follows from the
number of vectors, the window and the wanted chance of missing a pair that lies right at the threshold (closer pairs are
missed far more seldom). That chance is of a pair whose leading signs differ in every pass: where more vectors share
their leading signs than a window holds, they are compared with one another in blocks, however the vectors lie. If those
blocks came to more than all pairs, all pairs are compared once instead. Pairs found are united over the passes; the
links inside each united group are then counted exactly, in blocks.

Vectors move as they came (floats stay floats) and are made units of doubles where they are compared. Passes are laid out
a few at a time, so that what one lot of them shuffles and keeps on disk doesn't grow with their number.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fewbit.llm._components import components
from fewbit.llm._store import Stored, settled, table
from fewbit.llm.sharding import global_rank

THRESHOLD = 0.9
BLOCK = 2048
HALO = BLOCK // 2
SPAN = 4 * BLOCK
#: Vectors times passes that are laid out at a time; one pass at least.
LAID = 1 << 19
#: Groups of equal vectors with more rows than one in HOT of all meet their rows by broadcast: there are HOT of them at most.
HOT, COPIES = 10_000, 256
MISS = 1e-3
BITS = 62
SEED = 20261


def depth_for(n: int, halo: int = HALO) -> int:
    """Leading signs that leave `halo` of n evenly spread vectors together."""
    return min(BITS, math.ceil(math.log2(max(n / halo, 1))))


def passes_for(n: int, threshold: float = THRESHOLD, halo: int = HALO, miss: float = MISS) -> int:
    """Passes after which a pair at the threshold has been compared but for a chance of `miss`.

    A pass compares such a pair if their leading `depth_for(n)` signs agree.
    """
    agree = 1 - math.acos(threshold) / math.pi
    near = agree ** depth_for(n, halo)
    return 1 if near >= 1 - miss else math.ceil(math.log(miss) / math.log1p(-near))


def _comparable(single: bool):
    """(id, vector as bytes) of the vectors that can be compared; single: as floats, else as doubles."""
    kind = np.float32 if single else np.float64

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, out = [], []
            for i, v in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                if not v.is_valid or v.values.null_count:
                    continue
                x = v.values.to_numpy(zero_copy_only=False).astype(kind)
                if len(x) and np.isfinite(x).all() and x.any():
                    ids.append(i)
                    out.append(x.tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(out, pa.binary())], ["id", "v"])

    return run


def _units(vectors: list[bytes], single: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(positions, unit vectors in doubles) of the vectors of each dimension."""
    sizes = np.fromiter(map(len, vectors), np.int64, len(vectors)) // (4 if single else 8)
    for d in np.unique(sizes):
        some = np.flatnonzero(sizes == d)
        x = np.frombuffer(b"".join(vectors[i] for i in some), "<f4" if single else "<f8").reshape(-1, d).astype(np.float64)
        x /= np.abs(x).max(1, keepdims=True)
        yield some, x / np.linalg.norm(x, axis=1, keepdims=True)


def _keys(passes: range, single: bool):
    """(pass, key, id): the signs of a pass's random projections as one number."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        planes = {}
        weight = np.int64(1) << np.arange(BITS - 1, -1, -1, dtype=np.int64)
        for batch in batches:
            ids = batch.column(0).to_numpy(zero_copy_only=False)
            for some, x in _units(batch.column(1).to_pylist(), single):
                d = x.shape[1]
                for p in passes:
                    if (d, p) not in planes:
                        planes[d, p] = np.random.default_rng([SEED, d, p]).standard_normal((d, BITS))
                    key = ((x @ planes[d, p]) > 0) @ weight
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(some), p, np.int32)), pa.array(key), pa.array(ids[some])], ["pass", "key", "id"])

    return run


def _forest(near: np.ndarray) -> list[tuple[int, int]]:
    """(member, root) of each group of a symmetric boolean matrix, by breadth-first search over its rows."""
    out, left = [], near.any(axis=1)
    while left.any():
        root = int(left.argmax())
        left[root] = False
        front = near[root] & left
        while front.any():
            left &= ~front
            members = np.flatnonzero(front)
            out += [(int(m), root) for m in members]
            front = near[members].any(axis=0) & left
    return out


def _groups_of(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[tuple[tuple, list[list]]]:
    """Runs of rows with equal leading columns, from rows sorted by them: (key, the other columns' values)."""
    at, held = None, []
    for batch in batches:
        columns = [c.to_pylist() for c in batch.columns]
        for row in zip(*columns, strict=True):
            if row[:keys] != at:
                if held:
                    yield at, held
                at, held = row[:keys], []
            held.append(row[keys:])
    if held:
        yield at, held


def _neighbours(threshold: float, single: bool):
    """Links (a, b) that tie together the close vectors of each block."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, rows in _groups_of(batches, 1):
            ids = np.array([r[0] for r in rows])
            for some, x in _units([r[1] for r in rows], single):
                near = x @ x.T >= threshold
                np.fill_diagonal(near, False)
                tied = _forest(near)
                if tied:
                    pairs = ids[some[np.array(tied)]]
                    yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], ["a", "b"])

    return run


def _tiles(threshold: float, single: bool):
    """Links (a, b) that tie together the close vectors of each (bucket, i, j) pair of spans, found tile by tile."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for (*_, i, j), rows in _groups_of(batches, 4):
            ids, side = (np.array([r[k] for r in rows]) for k in (0, 1))
            for some, x in _units([r[2] for r in rows], single):
                left, right = (np.flatnonzero(side[some] == k) for k in (i, j))
                for p in range(0, len(left), BLOCK):
                    for q in range(p if i == j else 0, len(right), BLOCK):
                        one, other = left[p : p + BLOCK], right[q : q + BLOCK]
                        near = x[one] @ x[other].T >= threshold
                        if i == j and p == q:
                            np.fill_diagonal(near, False)
                        if not near.any():
                            continue
                        both, m = np.concatenate([one, other]), len(one)
                        square = np.zeros((len(both), len(both)), bool)
                        square[:m, m:], square[m:, :m] = near, near.T
                        pairs = ids[some[both[np.array(_forest(square))]]]
                        yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], ["a", "b"])

    return run


def _in_spans(rows: DataFrame, threshold: float, single: bool) -> DataFrame:
    """Links (a, b) among all rows of each (pass, bucket); rows are (pass, bucket, spans, id, v), spans the bucket's number of parts."""
    mine = rows.withColumn("mine", F.pmod(F.xxhash64("id"), F.col("spans")).cast("int"))
    pairs = mine.withColumn("other", F.explode(F.expr("sequence(0, spans - 1)"))).select(
        "pass", "bucket", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"), "id", "mine", "v"
    )
    keys = ["pass", "bucket", "i", "j"]
    return pairs.repartition(*keys).sortWithinPartitions(*keys).mapInArrow(_tiles(threshold, single), "a long, b long")


def _degrees(threshold: float, single: bool):
    """(id, links) of each (group, i, j) block pair; links count every copy of the other vector."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for (_, i, j), rows in _groups_of(batches, 3):
            ids, side, copies = (np.array([r[k] for r in rows]) for k in (0, 1, 2))
            links = np.zeros(len(rows), np.int64)
            for some, x in _units([r[3] for r in rows], single):
                near = x @ x.T >= threshold
                if i == j:
                    np.fill_diagonal(near, False)
                else:
                    near &= side[some][:, None] != side[some][None, :]
                links[some] = near @ copies[some]
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(links)], ["id", "links"])

    return run


def _keyed(groups: DataFrame, passes: range, single: bool) -> DataFrame:
    return groups.select("id", "v").mapInArrow(_keys(passes, single), "pass int, key long, id long")


def _found(groups: DataFrame, passes: range, crowded: DataFrame, depth: int, spans, threshold: float, single: bool) -> DataFrame:
    """Links (a, b) that some passes find: in windows of their order, and in buckets that hold more than a window does."""
    order = _keyed(groups, passes, single).withColumn("salt", F.xxhash64("id"))
    ranked = global_rank(order, ["pass", "key", "salt"])
    placed = ranked.select("id", F.expr(f"rank div {BLOCK}").alias("block"), F.expr(f"rank % {BLOCK} < {HALO}").alias("early"))
    spread = placed.select("id", F.explode(F.expr("CASE WHEN early AND block > 0 THEN array(block, block - 1) ELSE array(block) END")).alias("block"))
    dealt = spread.join(groups.select("id", "v"), "id").select("block", "id", "v").repartition("block").sortWithinPartitions("block")
    found = dealt.mapInArrow(_neighbours(threshold, single), "a long, b long")
    here = crowded.where(F.col("pass").between(passes.start, passes.stop - 1))
    if here.isEmpty():
        return found
    at = ranked.select("pass", F.shiftright("key", BITS - depth).alias("bucket"), "id")
    dense = at.join(here.select("pass", "bucket", spans(F.col("count"))), ["pass", "bucket"]).join(groups.select("id", "v"), "id")
    return found.unionByName(_in_spans(dense, threshold, single))


def embedding_groups(vectors: DataFrame, threshold: float = THRESHOLD, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """(id, n_links long, component_id long, kept boolean), one row per vector.

    Cosines are taken in double precision. Null, empty and zero vectors and those with null or non-finite components link
    with nothing; nor do vectors of different dimension. Equal vectors are compared once and counted as often as they
    come. Rows without id are left out; rows that repeat an id are one vector each under that id's component. An empty
    table gives an empty one. Only the two named columns are read; labels play no part.
    """
    rows = vectors.select(F.col(id_col).cast("long").alias("id"), F.col(vector_col).alias("v")).where("id IS NOT NULL")
    single = vectors.schema[vector_col].dataType.elementType.simpleString() == "float"
    unit = Stored(rows.mapInArrow(_comparable(single), "id long, v binary")).df
    groups = Stored(unit.groupBy("v").agg(F.min("id").alias("id"), F.count("*").alias("copies"))).df
    n, total = groups.agg(F.count("*"), F.coalesce(F.sum("copies"), F.lit(0))).first()
    passes, depth = passes_for(n, threshold), depth_for(n)
    bucket = F.shiftright("key", BITS - depth).alias("bucket")
    crowded = Stored(_keyed(groups, range(passes), single).groupBy("pass", bucket).count().where(F.col("count") > HALO)).df
    products = crowded.agg(F.sum(F.col("count") * F.col("count"))).first()[0] or 0
    spans = lambda count: F.ceil(count / SPAN).cast("int").alias("spans")
    if products > n * n:
        everyone = groups.select(F.lit(0).alias("pass"), F.lit(0).cast("long").alias("bucket"), spans(F.lit(n)), "id", "v")
        links = Stored(_in_spans(everyone, threshold, single)).df
    else:
        lots, at_a_time = [], max(1, LAID // max(n, 1))
        for first in range(0, passes, at_a_time):
            lot = range(first, min(first + at_a_time, passes))
            lots.append(settled(lambda lot=lot: _found(groups, lot, crowded, depth, spans, threshold, single)).df)
        links = reduce(DataFrame.unionByName, lots)
    group = Stored(components(links, "a", "b")).df
    group = group.unionByName(group.select(F.col("component").alias("node"), "component").distinct())

    members = groups.join(group, F.col("id") == F.col("node")).select("component", "id", "copies", "v")
    sizes = group.groupBy("component").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("blocks"))
    cut = members.join(sizes, "component").withColumn("mine", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int"))
    pairs = cut.withColumn("other", F.explode(F.expr("sequence(0, blocks - 1)"))).select(
        "component", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"), "id", "mine", "copies", "v"
    )
    pairs = pairs.repartition("component", "i", "j").sortWithinPartitions("component", "i", "j")
    degree = pairs.mapInArrow(_degrees(threshold, single), "id long, links long").groupBy("id").agg(F.sum("links").alias("links"))

    per_group = Stored(
        groups.join(degree, "id", "left").join(group.withColumnRenamed("node", "id"), "id", "left").select(
            "v", "copies", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.coalesce("component", "id").alias("component_id")
        )
    ).df
    many = F.col("copies") > max(COPIES, total // HOT)
    hot = F.broadcast(per_group.where(many).select("v", F.struct("n_links", "component_id").alias("hot")))
    known = unit.join(hot, "v", "left")
    rest = known.where("hot IS NULL").select("id", "v").join(per_group.where(~many), "v").select("id", "n_links", "component_id")
    found = known.where("hot IS NOT NULL").select("id", "hot.n_links", "hot.component_id").unionByName(rest)
    lone = rows.select("id").exceptAll(unit.select("id")).select("id", F.lit(0).cast("long").alias("n_links"), F.col("id").alias("component_id"))
    return found.unionByName(lone).select(F.col("id").alias(id_col), "n_links", "component_id", (F.col("id") == F.col("component_id")).alias("kept"))


def op1_embedding_neardup(spark, sf_dir):
    return embedding_groups(table(spark, sf_dir, "embeddings"))
