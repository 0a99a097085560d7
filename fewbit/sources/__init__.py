"""Reading the given tables and other formats, and the sharded store of samples."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name not in TABLES:
        raise ValueError(f"no table {name!r}")
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register(spark: SparkSession, sf_dir: str, names: list[str] | None = None) -> None:
    """The tables as temporary views, for SQL."""
    for name in names or TABLES:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def samples_schema(d: int) -> T.StructType:
    return T.StructType(
        [T.StructField("row_id", T.StringType()), T.StructField("worker_id", T.IntegerType()), T.StructField("split", T.StringType()), T.StructField("cls", T.IntegerType())]
        + [T.StructField(f"x{i}", T.DoubleType()) for i in range(d)]
    )


def read_samples(spark: SparkSession, path: str, fmt: str, schema: T.StructType) -> DataFrame:
    """Samples of another format (csv, json, orc, parquet) with a declared schema; a malformed row fails the read."""
    reader = spark.read.schema(schema)
    if fmt in ("csv", "json"):
        reader = reader.option("mode", "FAILFAST")
    if fmt == "csv":
        reader = reader.option("header", True)
    return reader.format(fmt).load(path)


def write_samples(df: DataFrame, path: str, fmt: str) -> None:
    writer = df.write.mode("overwrite").format(fmt)
    (writer.option("header", True) if fmt == "csv" else writer).save(path)


def write_shards(pts: DataFrame, path: str, files_per_worker: int = 1) -> None:
    """Samples as one folder per worker, so that a worker's pass reads its own files only.

    A large shard is dealt to several files by a hash of row_id; no task holds a whole worker then.
    """
    part = F.pmod(F.xxhash64("row_id"), F.lit(files_per_worker))
    laid = pts.withColumn("__part", part).repartition("worker_id", "__part").sortWithinPartitions("worker_id", "row_id").drop("__part")
    laid.write.mode("overwrite").partitionBy("worker_id").parquet(path)


def read_shards(spark: SparkSession, path: str, workers: list[int] | None = None) -> DataFrame:
    """The sharded samples; a list of workers becomes a partition filter."""
    pts = spark.read.parquet(path)
    return pts if workers is None else pts.where(F.col("worker_id").isin(*workers))


def work_dir(spark: SparkSession, name: str) -> str:
    """A new path in the folder all executors share: spark.checkpoint.dir, else the warehouse; a temporary folder in local mode only."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        folder = tempfile.mkdtemp(prefix="fewbit-") if spark.sparkContext.master.startswith("local") else spark.conf.get("spark.sql.warehouse.dir")
    return f"{folder.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def remove(spark: SparkSession, path: str) -> None:
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def remove_at_exit(spark: SparkSession, path: str) -> None:
    """Removes path when the driver ends: for results that are read after the query that wrote them has returned."""
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(at)


@contextmanager
def sharded(pts: DataFrame, files_per_worker: int = 1) -> Iterator[DataFrame]:
    """pts from a sharded store of its own, which is removed at the end."""
    path = work_dir(pts.sparkSession, "shards")
    write_shards(pts, path, files_per_worker)
    try:
        yield read_shards(pts.sparkSession, path)
    finally:
        remove(pts.sparkSession, path)


def write_runs(df: DataFrame, path: str) -> None:
    """Traces, ledgers or models by run: writing a run again replaces that run and no other."""
    df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("run_id").parquet(path)
