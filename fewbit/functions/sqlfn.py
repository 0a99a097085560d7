"""The library's functions under SQL names."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from fewbit.functions import theory
from fewbit.functions.codec import pack_column


def register_functions(spark: SparkSession) -> None:
    """fb_pack(array<bigint>, bits): a packed message; fb_epoch_min(target, L, mu, a, d, p): the epoch-length bound, null where
    no length does; fb_best_step(target, L, mu, d, p): the step that allows the shortest epoch."""

    @F.arrow_udf("binary")
    def fb_pack(index: pa.Array, bits: pa.Array) -> pa.Array:
        width = bits.to_numpy(zero_copy_only=False)
        if len(np.unique(width)) == 1:
            return pack_column(index, int(width[0]))
        out: list = [None] * len(index)
        for b in np.unique(width):
            some = np.flatnonzero(width == b)
            for i, message in zip(some, pack_column(index.take(pa.array(some)), int(b)).to_pylist(), strict=True):
                out[i] = message
        return pa.array(out, pa.binary())

    spark.udf.register("fb_pack", fb_pack)
    # formulas are SQL functions: no Python worker, and the optimizer sees through them
    number = lambda *names: ", ".join(f"{n} DOUBLE" for n in names)
    epoch = theory.epoch_sql("target", "l", "mu", "a", "d", "p")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION fb_epoch_min({number('target', 'l', 'mu', 'a', 'd', 'p')}) RETURNS DOUBLE RETURN {epoch}")
    best = theory.best_step_sql("target", "l", "mu", "d", "p")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION fb_best_step({number('target', 'l', 'mu', 'd', 'p')}) RETURNS DOUBLE RETURN {best}")
