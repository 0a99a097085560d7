"""Learning tasks on the given tables: (row_id, worker_id, split, cls, x) with cls 0/1 or a class number."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from fewbit.sources import load

CHARGE_CUT = 50_000.0
BUCKETS, LANGUAGE_SCALE, STRETCH = 784, 3.0, 1000
LANGUAGES = ("en", "fr", "de", "es")
#: Event types with a feature each; all others have none of the four.
EVENT_TYPES = ("click", "view", "purchase", "signup")


def threshold_label(value: Column, cut: float) -> Column:
    """A continuous output made a class: 1 above the cut, else 0."""
    return F.when(value > cut, 1).otherwise(0).cast("int")


def signed(cls: Column, positive: int = 1) -> Column:
    """+1 for the positive class, -1 for the others."""
    return F.when(cls == positive, 1.0).otherwise(-1.0)


def _hex(text: str, digits: int) -> Column:
    return F.expr(f"CAST(conv(substring(md5({text}), 1, {digits}), 16, 10) AS BIGINT)")


def charge_wide(spark: SparkSession, sf_dir: str, workers: int = 10, merged: bool = False) -> DataFrame:
    """Line items with their parts, d = 9; class 1 if the charged price exceeds the cut. Columns x0..x8.

    merged: without row_id, and items alike in worker, split and all that makes their class and features once, with their
    number as `weight`. Classes and features are made of what is left, and no column that others tell is compared.
    """
    items, part = load(spark, sf_dir, "lineitem"), load(spark, sf_dir, "part").select("p_partkey", "p_size")
    j = items.join(part, items.l_partkey == part.p_partkey)
    key = "concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_shipdate)"
    # what tells most items apart comes first, as comparing ends there
    made_of = ["l_extendedprice", "l_quantity", "l_discount", "l_tax", "l_linenumber", "p_size"]
    rows = j.select(
        *made_of,
        F.month("l_shipdate").alias("month"),
        F.dayofweek("l_shipdate").alias("weekday"),
        F.pmod("l_orderkey", F.lit(workers)).cast("int").alias("worker_id"),
        (_hex(key, 8) % 5 == 0).alias("test"),
        F.expr(f"md5({key})").alias("row_id"),
    )
    own = ["row_id"]
    if merged:
        rows, own = rows.drop("row_id").groupBy(*made_of, "month", "weekday", "worker_id", "test").agg(F.count("*").alias("weight")), []
    out = F.col("l_extendedprice") * (1 - F.col("l_discount")) * (1 + F.col("l_tax"))
    x = [
        (F.col("l_quantity") - 25.5) / 24.5,
        (F.col("l_extendedprice") - 53000) / 52500,
        (F.col("l_discount") - 0.05) / 0.05,
        (F.col("l_tax") - 0.04) / 0.04,
        (F.col("l_linenumber") - 4) / 3.0,
        (F.col("p_size") - 25.5) / 24.5,
        (F.col("month") - 6.5) / 5.5,
        (F.col("weekday") - 1 - 3) / 3.0,
        F.lit(1.0),
    ]
    return rows.select(
        *own,
        "worker_id",
        F.when(F.col("test"), "test").otherwise("train").alias("split"),
        threshold_label(out, CHARGE_CUT).alias("cls"),
        *[c.cast("double").alias(f"x{i}") for i, c in enumerate(x)],
        *(["weight"] if merged else []),
    )


def narrow(wide: DataFrame, d: int = 9) -> DataFrame:
    """Columns x0.. as one array."""
    return wide.select("row_id", "worker_id", "split", "cls", F.array(*[f"x{i}" for i in range(d)]).alias("x"))


def charge(spark: SparkSession, sf_dir: str, workers: int = 10) -> DataFrame:
    return narrow(charge_wide(spark, sf_dir, workers))


def _vectors(spark, sf_dir, cls: Column, workers: int) -> DataFrame:
    return load(spark, sf_dir, "embeddings").select(
        F.col("vec_id").cast("string").alias("row_id"),
        F.pmod(F.expr("vec_id div 5"), F.lit(workers)).cast("int").alias("worker_id"),  # ids' residues by 5 tell the split
        F.when(F.col("vec_id") % 5 == 0, "test").otherwise("train").alias("split"),
        cls.cast("int").alias("cls"),
        F.col("embedding").cast("array<double>").alias("x"),
    )


def anchor10(spark: SparkSession, sf_dir: str, workers: int = 10) -> DataFrame:
    """Ten classes, d = 64: which of the first ten coordinates is largest."""
    return _vectors(spark, sf_dir, F.expr("array_position(slice(embedding, 1, 10), array_max(slice(embedding, 1, 10))) - 1"), workers)


def noise10(spark: SparkSession, sf_dir: str, workers: int = 10) -> DataFrame:
    """The negative control: the given labels, which the vectors don't tell."""
    return _vectors(spark, sf_dir, F.col("label"), workers)


def distinct_texts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, lang, fold, text) of each distinct text of three characters or more, that of its smallest doc_id.

    Texts are told apart by 128 bits of hash, so only hashes and ids are shuffled; the rows kept are then found by their ids.
    """
    docs = load(spark, sf_dir, "documents").select("doc_id", "text", "lang").where("length(text) >= 3")
    own = docs.groupBy(F.md5("text").alias("h")).agg(F.min("doc_id").alias("doc_id"))
    return docs.join(own, "doc_id").where(F.md5("text") == F.col("h")).select("doc_id", "lang", (_hex("text", 8) % 5).alias("fold"), "text").dropDuplicates(["doc_id"])


def _count_trigrams(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(.., idx, n) of (text, ..): non-empty buckets of each whole text and their counts, computed over many texts at once."""
    known: dict[int, int] = {}
    # bucket + 1 of trigrams of the first 256 code points, as they are met
    table = np.zeros(1 << 24, np.int16)
    for batch in batches:
        for lo in range(0, batch.num_rows, 64):
            part = batch.slice(lo, 64)
            total = np.zeros(part.num_rows * BUCKETS, np.int64)
            pieces: list[tuple[int, str]] = []
            for i, text in enumerate(part.column(0).to_pylist()):
                for at in range(0, len(text) - 2, STRETCH):
                    # a stretch ends with the last trigram that begins in it
                    pieces.append((i, text[at : at + STRETCH + 2]))
                    if len(pieces) == 256:
                        _add_trigrams(pieces, total, known, table)
                        pieces = []
            if pieces:
                _add_trigrams(pieces, total, known, table)
            rows = total.reshape(part.num_rows, BUCKETS)
            owner, idx = np.nonzero(rows)
            ends = pa.array(np.searchsorted(owner, np.arange(part.num_rows + 1)).astype(np.int32))
            lists = [pa.ListArray.from_arrays(ends, pa.array(v)) for v in (idx.astype(np.int32), rows[owner, idx])]
            yield pa.RecordBatch.from_arrays([*part.columns[1:], *lists], [*part.schema.names[1:], "idx", "n"])


def _bucket(g: int) -> int:
    letters = chr(g >> 42) + chr(g >> 21 & 0x1FFFFF) + chr(g & 0x1FFFFF)
    return int(hashlib.md5(letters.encode()).hexdigest()[:8], 16) % BUCKETS


def _add_trigrams(pieces: list[tuple[int, str]], total: np.ndarray, known: dict[int, int], table: np.ndarray) -> None:
    code = np.frombuffer("".join(s for _, s in pieces).encode("utf-32-le"), "<u4").astype(np.int64)
    size = np.array([len(s) for _, s in pieces])
    owner = np.repeat([i for i, _ in pieces], size)
    begins = np.ones(len(code), bool)
    begins[np.concatenate([np.cumsum(size) - 1, np.cumsum(size) - 2])] = False
    at = np.flatnonzero(begins)
    a, b, c = code[at], code[at + 1], code[at + 2]
    low = (a | b | c) < 256
    bucket = np.empty(len(at), np.int64)
    key = (a << 16 | b << 8 | c)[low]
    for g in np.unique(key[table[key] == 0]).tolist():
        table[g] = _bucket(g >> 16 << 42 | (g >> 8 & 255) << 21 | g & 255) + 1
    bucket[low] = table[key].astype(np.int64) - 1
    if not low.all():
        gram, inverse = np.unique((a << 42 | b << 21 | c)[~low], return_inverse=True)
        if len(known) > 1 << 17:
            known.clear()
        for g in gram.tolist():
            if g not in known:
                known[g] = _bucket(g)
        bucket[~low] = np.array([known[g] for g in gram.tolist()])[inverse]
    total += np.bincount(owner[at] * BUCKETS + bucket, minlength=len(total))


def _counted(own: DataFrame) -> DataFrame:
    """own with (idx, n) in place of its text."""
    rest = own.drop("text")
    return own.select("text", *rest.columns).mapInArrow(_count_trigrams, T.StructType([*rest.schema.fields, T.StructField("idx", T.ArrayType(T.IntegerType())), T.StructField("n", T.ArrayType(T.LongType()))]))


def language_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, bucket, n): hashed character trigrams of each distinct text, the whole of it; counted within the row."""
    cells = _counted(distinct_texts(spark, sf_dir).select("doc_id", "text")).select("doc_id", F.explode(F.arrays_zip("idx", "n")).alias("c"))
    return cells.select("doc_id", F.col("c.idx").alias("bucket"), F.col("c.n").alias("n"))


def _language_counts(spark: SparkSession, sf_dir: str, workers: int) -> DataFrame:
    cls = F.array_position(F.array(*map(F.lit, LANGUAGES)), F.col("lang")) - 1
    return _counted(distinct_texts(spark, sf_dir)).select(
        F.col("doc_id").cast("string").alias("row_id"),
        F.pmod("doc_id", F.lit(workers)).cast("int").alias("worker_id"),
        F.when(F.col("fold") == 0, "test").otherwise("train").alias("split"),
        cls.cast("int").alias("cls"),
        "idx",
        "n",
        F.lit(LANGUAGE_SCALE).alias("scale"),
        F.expr("sqrt(aggregate(n, 0D, (s, v) -> s + v * v))").alias("norm"),
    )


def language(spark: SparkSession, sf_dir: str, workers: int = 10) -> DataFrame:
    """Which language a text is in, d = 784: trigram counts scaled to norm 3, kept sparse as (idx, val)."""
    return _language_counts(spark, sf_dir, workers).select("row_id", "worker_id", "split", "cls", "idx", F.expr("transform(n, v -> scale * v / norm)").alias("val"))


def quality(spark: SparkSession, sf_dir: str, workers: int = 10) -> DataFrame:
    """Good or bad documents by nine plain features; classes are unbalanced."""
    d = load(spark, sf_dir, "documents").join(load(spark, sf_dir, "labels").where("quality IS NOT NULL"), "doc_id")
    n = F.greatest(F.length("text"), F.lit(1))
    share = lambda pattern: F.regexp_count("text", F.lit(pattern)) / n
    words = F.size(F.split("text", r"\s+"))
    rows = F.split("text", "\n")
    x = [F.log(n) / 10, F.log(words) / 10, n / words / 10, share("[0-9]"), share("[^\\p{L}\\s0-9]"), share("\\p{Lu}"), 1 - F.size(F.array_distinct(rows)) / F.size(rows), F.when(F.col("lang") == "en", 1.0).otherwise(0.0), F.lit(1.0)]
    return d.select(
        F.col("doc_id").cast("string").alias("row_id"),
        F.pmod("doc_id", F.lit(workers)).cast("int").alias("worker_id"),
        F.when(_hex("text", 8) % 5 == 0, "test").otherwise("train").alias("split"),
        F.col("quality").cast("int").alias("cls"),
        F.array(*[c.cast("double") for c in x]).alias("x"),
    )


def sensor_features() -> list[Column]:
    turn = (F.hour("ts") + F.minute("ts") / 60) * 0.2617993877991494
    kinds = [F.when(F.col("event_type") == kind, 1.0).otherwise(0.0) for kind in EVENT_TYPES]
    return [F.sin(turn), F.cos(turn), (F.dayofweek("ts") - 4) / 3.0, F.when(F.dayofweek("ts").isin(1, 7), 1.0).otherwise(0.0), *kinds, F.lit(1.0)]


def sensor_of(events: DataFrame, workers: int = 10) -> DataFrame:
    """Events, batch or stream, as samples: does a reading exceed 35? No signal is expected."""
    return events.select(
        F.col("event_id").cast("string").alias("row_id"),
        F.pmod("user_id", F.lit(workers)).cast("int").alias("worker_id"),
        F.when(F.col("event_id") % 5 == 0, "test").otherwise("train").alias("split"),
        threshold_label(F.col("value"), 35.0).alias("cls"),
        F.array(*[c.cast("double") for c in sensor_features()]).alias("x"),
        "ts",
    )


def sensor(spark: SparkSession, sf_dir: str, workers: int = 10) -> DataFrame:
    return sensor_of(load(spark, sf_dir, "events"), workers).drop("ts")


TASKS = {"charge": (charge, 9, 2), "language": (language, BUCKETS, 4), "anchor10": (anchor10, 64, 10), "noise10": (noise10, 64, 10), "quality": (quality, 9, 2), "sensor": (sensor, 9, 2)}


def samples(spark: SparkSession, sf_dir: str, task: str, workers: int = 10) -> DataFrame:
    """(worker_id, split, cls, features) of a task for its runs and measures, in the least space: equal dense samples come
    once, with the number of their rows as `weight`, sparse ones with their whole counts."""
    if task == "language":
        return _language_counts(spark, sf_dir, workers).drop("row_id").withColumn("n", F.col("n").cast("array<int>"))
    if task == "charge":
        # merged before the features are an array
        wide = charge_wide(spark, sf_dir, workers, merged=True)
        x = [c for c in wide.columns if c.startswith("x")]
        return wide.select("worker_id", "split", "cls", F.array(*x).alias("x"), "weight")
    pts = TASKS[task][0](spark, sf_dir, workers).drop("row_id")
    return pts.groupBy(*pts.columns).agg(F.count("*").alias("weight"))
