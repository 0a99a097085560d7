"""Reading tables and keeping intermediate results where every executor can reach them."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_LOCAL: dict[str, str] = {}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir, else the warehouse; a temporary one only in local mode."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder.rstrip("/")
    if spark.sparkContext.master.startswith("local"):
        return _LOCAL.setdefault("dir", tempfile.mkdtemp(prefix="fewbit-"))
    return spark.conf.get("spark.sql.warehouse.dir").rstrip("/")


#: Bytes that a batch of rows on its way to a Python worker holds, about; a longer row is a batch by itself.
BATCH = "4m"


@contextmanager
def small_batches(spark: SparkSession) -> Iterator[None]:
    """While a job is run: batches bounded by bytes, so that neither side holds thousands of long texts at a time."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    before = spark.conf.get(key)
    spark.conf.set(key, BATCH)
    try:
        yield
    finally:
        spark.conf.set(key, before)


class Stored:
    """A DataFrame written as Parquet in the shared folder; its lineage is cut there and it outlives any executor.

    It goes with `drop`, with the scope it was made in (`settled`), or when the driver ends.
    """

    def __init__(self, df: DataFrame, codec: str = "zstd"):
        self.spark = df.sparkSession
        self.path = f"{shared_dir(self.spark)}/stored-{uuid.uuid4().hex}"
        with small_batches(self.spark):
            df.write.option("compression", codec).parquet(self.path)
        self.df = self.spark.read.schema(df.schema).parquet(self.path)
        at, files = self._place()
        files.deleteOnExit(at)
        if _SCOPES:
            _SCOPES[-1].append(self)

    def _place(self):
        at = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self.path)
        return at, at.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())

    def drop(self) -> None:
        at, files = self._place()
        files.delete(at, True)


_SCOPES: list[list[Stored]] = []


def stored(df: DataFrame) -> DataFrame:
    return Stored(df).df


def settled(make: Callable[[], DataFrame]) -> Stored:
    """The table of what make gives; the tables that make kept on the way are dropped once it is written."""
    _SCOPES.append([])
    try:
        out = Stored(make())
    finally:
        made = _SCOPES.pop()
    for other in made:
        if other is not out:
            other.drop()
    return out


def sifted(rows: DataFrame, ids: DataFrame, key: str, bits: int = 23) -> DataFrame:
    """rows with `__maybe boolean`: false where key is certainly not among ids (a one-column table).

    ids become a bitmap of hashes, 2**bits bits in all whatever their number, so broadcasting it is safe (1 MB). Where ids
    outgrow it, more rows pass and the exact join behind it does all the work; the answer is the same.
    """
    spot = lambda c: F.pmod(F.xxhash64(c), F.lit(1 << bits))
    bitmap = ids.select(spot(F.col(ids.columns[0])).alias("h")).groupBy(F.expr("h div 32768").alias("__bucket")).agg(
        F.bitmap_construct_agg(F.col("h") % 32768).alias("__bitmap")
    )
    at = rows.withColumn("__h", spot(F.col(key))).withColumn("__bucket", F.expr("__h div 32768"))
    byte = "CAST(conv(hex(substring(__bitmap, CAST(__h % 32768 div 8 AS INT) + 1, 1)), 16, 10) AS INT)"
    bit = F.expr(f"coalesce(shiftright({byte}, CAST(__h % 8 AS INT)) % 2 = 1, false)")
    return at.join(F.broadcast(bitmap), "__bucket", "left").withColumn("__maybe", bit).drop("__h", "__bucket", "__bitmap")
