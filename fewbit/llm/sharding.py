"""Sharding along a Hilbert curve over quantised metadata, so that files can be pruned on several dimensions at once."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window

from fewbit.llm._store import stored, table

BITS = 5


def hilbert_index(cells: np.ndarray, bits: int) -> np.ndarray:
    """Curve position of each row of integer cells (rows x dimensions, each below 2**bits).

    Undoes the curve's rotations from the highest bit down, Gray-decodes the axes, then interleaves their bits.
    """
    x = cells.astype(np.int64).copy()
    n = x.shape[1]
    q = 1 << (bits - 1)
    while q > 1:
        low = q - 1
        for d in range(n):
            on = (x[:, d] & q) != 0
            swap = np.where(on, 0, (x[:, 0] ^ x[:, d]) & low)
            x[:, 0] ^= np.where(on, low, swap)
            x[:, d] ^= swap
        q >>= 1
    for d in range(1, n):
        x[:, d] ^= x[:, d - 1]
    t = np.zeros(len(x), np.int64)
    q = 1 << (bits - 1)
    while q > 1:
        t ^= np.where((x[:, n - 1] & q) != 0, q - 1, 0)
        q >>= 1
    x ^= t[:, None]
    out = np.zeros(len(x), np.int64)
    for bit in range(bits - 1, -1, -1):
        for d in range(n):
            out = (out << 1) | ((x[:, d] >> bit) & 1)
    return out


def label_cell(col: Column, bits: int = BITS) -> Column:
    """Cell of a label column: a hash, so that one label is always one cell; null has its own hash."""
    return F.pmod(F.xxhash64(F.coalesce(col.cast("string"), F.lit("\0"))), F.lit(1 << bits)).cast("int")


def size_cell(col: Column, bits: int = BITS) -> Column:
    """Cell of a size: two cells for each doubling."""
    return F.least(F.floor(2 * F.log2(F.greatest(col, F.lit(1)))), F.lit((1 << bits) - 1)).cast("int")


def global_rank(rows: DataFrame, keys: Sequence[str], rank: str = "rank") -> DataFrame:
    """rows with a gapless long `rank` from 0 in the order of keys.

    The order is range-partitioned, so equal or hot leading keys are split by the later ones; a task numbers its own
    stretch, and stretches are shifted by the counts of those before them (one row per partition).
    """
    laid = stored(
        rows.repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn("__at", F.monotonically_increasing_id())
    ).withColumn("__part", F.shiftright("__at", 33))
    counts = laid.groupBy("__part").count()
    ahead = Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)
    shift = counts.select("__part", F.coalesce(F.sum("count").over(ahead), F.lit(0)).alias("__shift"))
    return laid.join(F.broadcast(shift), "__part").withColumn(rank, F.col("__shift") + F.col("__at").bitwiseAND((1 << 33) - 1)).drop(
        "__part", "__at", "__shift"
    )


def hilbert_shards(docs: DataFrame, shards: int = 40, labels: Sequence[str] = ("lang", "source"), bits: int = BITS) -> DataFrame:
    """(doc_id, size, text_crc32, curve, shard, slot): every document laid along the curve and the curve cut in equal runs.

    Dimensions are the label columns and the size of the text. Law `rows`: shards differ by one row at most, whatever
    the data. Equal texts take the metadata of their smallest labels, so they lie side by side (a group larger than a
    shard fills neighbouring ones). Order: curve, text hash, doc_id; rows that repeat a doc_id keep a slot each. Null
    text counts as empty. Missing label columns are not dimensions. An empty table gives an empty one. Other columns of
    docs are not read.
    """
    labels = [c for c in labels if c in docs.columns]
    text = F.coalesce("text", F.lit(""))
    slim = stored(
        docs.select(
            "doc_id",
            (F.octet_length(text) + 16).cast("long").alias("size"),
            F.crc32(text.cast("binary")).alias("text_crc32"),
            F.xxhash64(text).alias("th"),
            *[label_cell(F.col(c), bits).alias(f"cell{i}") for i, c in enumerate(labels)],
        )
    )
    cells = [f"cell{i}" for i in range(len(labels))]
    same = ["th", "text_crc32", "size"]
    groups = slim.groupBy(*same).agg(F.min(F.struct(*cells)).alias("c") if cells else F.lit(None).alias("c"))
    groups = groups.select(*same, F.array(*[F.col(f"c.{c}") for c in cells], size_cell(F.col("size"), bits)).alias("cells"))

    def curve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at = b.column(3).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1)
            yield pa.RecordBatch.from_arrays([*b.columns[:3], pa.array(hilbert_index(at, bits))], [*same, "curve"])

    on_curve = groups.mapInArrow(curve, "th long, text_crc32 long, size long, curve long")
    placed = slim.select("doc_id", *same).join(on_curve, same)
    ranked = global_rank(placed, ["curve", "th", "doc_id"])
    n = max(1, slim.count())
    shard = F.expr(f"rank * {shards} div {n}")
    first = F.expr(f"(shard * {n} + {shards - 1}) div {shards}")
    return ranked.withColumn("shard", shard).select(
        "doc_id", "size", "text_crc32", "curve", F.col("shard").cast("int").alias("shard"), (F.col("rank") - first).alias("slot")
    )


#: Bytes of text that one file of a shard holds, about.
FILE = 512 << 20


def write_shards(docs: DataFrame, placed: DataFrame, path: str, file_bytes: int = FILE) -> None:
    """Whole documents as one Parquet folder per shard, its files successive runs of slots; footers then prune on every dimension.

    placed: doc_id, size, shard and slot of each document. A shard larger than a file is dealt to several tasks by ranges.
    """
    own = placed.select("doc_id", "shard", "slot")
    whole = placed.agg(F.countDistinct("shard").alias("shards"), F.coalesce(F.sum("size"), F.lit(0)).alias("size")).first()
    files = max(whole["shards"], 1) + int(whole["size"] // file_bytes)
    full = docs.drop(*[c for c in ("shard", "slot") if c in docs.columns]).join(own, "doc_id")
    full.repartitionByRange(files, "shard", "slot").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)


def op7_hilbert_sharding(spark, sf_dir):
    out = hilbert_shards(table(spark, sf_dir, "documents"))
    return out.select(
        "doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast(T.IntegerType()).alias("grown_shard"), "curve"
    )
