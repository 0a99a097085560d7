"""Measures of runs: on the samples (loss, F1) and on traces, ledgers and messages."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from fewbit.operators.objective import columns_of, matrix, weights


def confusion(pts: DataFrame, models: dict[str, dict[int, np.ndarray]], d: int) -> DataFrame:
    """(name, cls, rule, tp, fp, fn) of one-vs-all model sets {name: {class: model}} on samples.

    rule sign: a class is predicted where its own score is positive; argmax: where its score is the largest, of equals the
    smallest class. Each task sends sums only.
    """
    names = list(models)

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple, np.ndarray] = {}
        for b in batches:
            x, cls, weight = matrix(b, d), b.column(1).to_numpy(), weights(b)
            rows = np.ones(len(cls), np.int64) if weight is None else weight.astype(np.int64)
            for name in names:
                order = sorted(models[name])
                score = x @ np.array([models[name][c] for c in order]).T
                best = score.argmax(1)
                for i, c in enumerate(order):
                    true = cls == c
                    for rule, said in (("sign", score[:, i] > 0), ("argmax", best == i)):
                        if rule == "argmax" and len(order) == 1:
                            said = score[:, i] > 0
                        counts = np.array([rows[said & true].sum(), rows[said & ~true].sum(), rows[~said & true].sum()])
                        held[name, c, rule] = held.get((name, c, rule), 0) + counts
        if held:
            columns = [list(c) for c in zip(*((*k, *v.tolist()) for k, v in held.items()), strict=True)]
            kinds = [pa.string(), pa.int32(), pa.string(), pa.int64(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], ["name", "cls", "rule", "tp", "fp", "fn"])

    parts = pts.select(*columns_of(pts)).mapInArrow(partial, "name string, cls int, rule string, tp long, fp long, fn long")
    return parts.groupBy("name", "cls", "rule").agg(*[F.sum(c).alias(c) for c in ("tp", "fp", "fn")])


def f1(counts: DataFrame) -> DataFrame:
    """counts with f1 of each class; 0 where nothing is right."""
    whole = 2 * F.col("tp") + F.col("fp") + F.col("fn")
    return counts.withColumn("f1", F.when(whole > 0, 2 * F.col("tp") / whole).otherwise(0.0))


def f1_macro(counts: DataFrame) -> DataFrame:
    """(name, rule, f1_macro): the plain mean over classes."""
    return f1(counts).groupBy("name", "rule").agg(F.avg("f1").alias("f1_macro"))


def gap(trace: DataFrame, optimum: float) -> DataFrame:
    return trace.withColumn("gap", F.col("loss") - F.lit(optimum))


def contraction(trace: DataFrame) -> DataFrame:
    """trace of gap() with the ratio of each gap to the one before; null after a gap of zero."""
    w = Window.partitionBy("run_id").orderBy("k")
    return trace.withColumn("contraction", F.try_divide("gap", F.lag("gap").over(w)))


def plateau(trace: DataFrame, last: int = 5) -> DataFrame:
    """Where runs stall: least and mean gap of the last rounds."""
    w = Window.partitionBy("run_id").orderBy(F.desc("k"))
    tail = trace.withColumn("back", F.row_number().over(w)).where(F.col("back") <= last)
    return tail.groupBy("run_id").agg(F.min("gap").alias("gap_min"), F.avg("gap").alias("gap_mean"))


def to_target(trace: DataFrame, measure: str, level: float) -> DataFrame:
    """(run_id, first round, bits so far) at which a measure is down to a level; null if never."""
    hit = F.col(measure) <= level
    return trace.groupBy("run_id").agg(F.min(F.when(hit, F.col("k"))).alias("k"), F.min(F.when(hit, F.col("cum_bits_paper"))).alias("bits"))


def round_error(messages: DataFrame) -> DataFrame:
    """Mean square rounding error by round and kind of message."""
    return messages.groupBy("run_id", "k", "kind").agg(F.avg("sq_error").alias("mse"), F.sum("saturated").alias("saturated"))


def bits_by_direction(messages: DataFrame) -> DataFrame:
    """Bits that travelled, by run, direction and kind, with subtotals."""
    return messages.where("travels").rollup("run_id", "direction", "kind").agg(F.sum("bits").alias("bits"), F.count("*").alias("n"))
