"""Streams of samples: training by micro-batches, windows with late data, state by worker."""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

EVENTS = T.StructType(
    [T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampType()), T.StructField("user_id", T.LongType()), T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType())]
)


def event_stream(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    """A folder (or a glob) of event files as a stream."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files).parquet(path)


def unique(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    """Without the repeats of at-least-once sources, within the watermark."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def windowed_sums(stream: DataFrame, late: str = "1 hour", length: str = "1 day", slide: str | None = None) -> DataFrame:
    """Rows and value sums by worker and window; rows later than the watermark are dropped."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return stream.withWatermark("ts", late).groupBy(w.alias("w"), F.pmod("user_id", F.lit(10)).cast("int").alias("worker_id")).agg(F.count("*").alias("n"), F.sum("value").alias("s"))


def sessions(stream: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))


def worker_state(stream: DataFrame) -> DataFrame:
    """(worker_id, n, mean): the running mean of each worker's readings, kept as state between batches."""

    def update(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, total = state.get if state.exists else (0, 0.0)
        for f in frames:
            n, total = n + len(f), total + float(f["value"].sum())
        state.update((n, total))
        yield pd.DataFrame({"worker_id": [int(key[0])], "n": [n], "mean": [total / max(n, 1)]})

    keyed = stream.select(F.pmod("user_id", F.lit(10)).cast("int").alias("worker_id"), "value")
    return keyed.groupBy("worker_id").applyInPandasWithState(update, "worker_id int, n long, mean double", "n long, total double", "update", "NoTimeout")


def with_model(stream: DataFrame, models: DataFrame, on: str = "worker_id") -> DataFrame:
    """A stream beside a static table of models, broadcast if it is small: every batch meets the table as it was at the start."""
    return stream.join(models, on)


class LateRows:
    """Counts, by micro-batch, the rows whose window had closed before they came: those that the windowed sums drop.

    The rule is the engine's: rows are late by the watermark of the batch before, which follows from the greatest time of
    the batches before that one, less the delay. For `foreachBatch`; a batch that comes again is counted once.
    """

    def __init__(self, delay: str = "1 hour", length: str = "1 day"):
        self.delay, self.length, self.top, self.next_top, self.counts = delay, length, None, None, {}

    def __call__(self, batch: DataFrame, number: int) -> None:
        if number in self.counts:
            return
        closed = F.lit(False)
        if self.top is not None:
            closed = F.window("ts", self.length)["end"] <= F.lit(self.top) - F.expr(f"INTERVAL {self.delay}")
        r = batch.select("ts", F.coalesce(closed, F.lit(False)).alias("late")).agg(F.count("*").alias("n"), F.sum(F.col("late").cast("long")).alias("late"), F.max("ts").alias("top")).first()
        self.counts[number] = (r["n"], r["late"] or 0)
        self.top = self.next_top
        if r["top"] is not None and (self.next_top is None or r["top"] > self.next_top):
            self.next_top = r["top"]


class StreamTrainer:
    """One epoch of a method per micro-batch of samples, from the model that the batch before it left.

    With a path, the state after each batch is kept there; a trainer made anew on the same path goes on from the last one.
    A batch that comes again after a failure is known by its number and changes nothing.
    """

    def __init__(self, d: int, step: float = 0.2, lam: float = 0.1, path: str | None = None, spark: SparkSession | None = None, method: str = "qavrm_adaptive_plus", steps: int = 8):
        self.d, self.step, self.lam, self.path, self.method, self.steps = d, step, lam, path, method, steps
        self.model, self.last = np.zeros(d), -1
        self.trace: list[tuple[int, int, float, float]] = []
        if path and (was := self._kept(spark or SparkSession.getActiveSession())):
            self.last, self.model, self.trace = was["last"], np.array(was["model"]), [tuple(t) for t in was["trace"]]

    def _kept(self, spark: SparkSession) -> dict | None:
        at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self.path)
        if not at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(at):
            return None
        rows = spark.read.schema("state string, batch long").text(self.path).orderBy(F.desc("batch")).limit(1).collect()
        return json.loads(rows[0]["state"]) if rows else None

    def __call__(self, batch: DataFrame, number: int) -> None:
        from fewbit.plans.config import Config
        from fewbit.plans.driver import Run, fit_many
        from fewbit.plans.engines import measured

        if number <= self.last:
            return
        held = batch.persist()
        sizes = {r[0]: r[1] for r in held.groupBy("worker_id").count().collect()}
        if sizes:
            config = Config(workers=len(sizes), rounds=1, steps=self.steps, step=self.step, lam=self.lam, seed=number, start=self.model.tolist())
            out = fit_many(held, [Run(self.method, config)], self.d, measured(held, self.d)).states[0]
            self.trace.append((number, sum(sizes.values()), float(out.trace[0][5]), float(out.trace[0][6])))
            self.model = out.kept.model
        held.unpersist()
        self.last = number
        if self.path:
            state = json.dumps({"last": number, "model": self.model.tolist(), "trace": self.trace})
            # a folder a batch: the state before it stays until this one is whole
            batch.sparkSession.createDataFrame([(state,)], "state string").coalesce(1).write.mode("overwrite").text(f"{self.path}/batch={number}")
