"""Formats, the sharded store and the run store as queries: written, read again, summed up, removed."""

from __future__ import annotations

from pyspark.sql import functions as F

from fewbit.operators import tasks
from fewbit.plans.driver import Run, fit_many
from fewbit.plans.config import Config
from fewbit.queries.methods import SEED, train
from fewbit.queries.twin import CHARGE, D
from fewbit.sources import load, read_samples, read_shards, remove, samples_schema, work_dir, write_runs, write_samples, write_shards


def _summed(df):
    return df.groupBy("worker_id", "split").agg(F.count("*").alias("n"), *[(F.round(F.sum(f"x{i}"), 5) + 0.0).alias(f"s{i}") for i in range(D)])


def _kept(spark, df):
    return spark.createDataFrame(df.collect(), df.schema)


def formats(spark, sf_dir):
    """Samples by way of CSV, JSON lines and ORC with a declared schema."""
    wide, parts = tasks.charge_wide(spark, sf_dir), []
    for fmt in ("csv", "json", "orc"):
        path = work_dir(spark, fmt)
        write_samples(wide, path, fmt)
        parts.append(_kept(spark, _summed(read_samples(spark, path, fmt, samples_schema(D))).withColumn("fmt", F.lit(fmt))))
        remove(spark, path)
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


PICKED = (3, 7)


def pruned_shards(spark, sf_dir):
    """Two workers from the sharded store: the other folders aren't read."""
    path = work_dir(spark, "shards")
    write_shards(tasks.charge_wide(spark, sf_dir), path)
    out = _kept(spark, _summed(read_shards(spark, path, list(PICKED))))
    remove(spark, path)
    return out


def run_store(spark, sf_dir):
    """Traces of two runs, one of them written twice: the second writing replaces the first and nothing else."""
    pts, path = train(spark, sf_dir), work_dir(spark, "runs")
    gd, sag = (fit_many(pts, [Run(m, Config(rounds=n, seed=SEED), run_id=m)], D, "measured").trace(spark) for m, n in (("gd", 2), ("sag", 4)))
    again = fit_many(pts, [Run("gd", Config(rounds=3, seed=SEED), run_id="gd")], D, "measured").trace(spark)
    pts.unpersist()
    for trace in (gd, sag, again):
        write_runs(trace, path)
    out = _kept(spark, spark.read.parquet(path).groupBy("run_id").agg(F.count("*").alias("n"), F.max("k").alias("k"), F.sum("bits_paper").alias("bits")))
    remove(spark, path)
    return out


def tables(spark, sf_dir):
    """Every table by its name: rows."""
    from fewbit.sources import TABLES

    parts = [load(spark, sf_dir, t).agg(F.lit(t).alias("name"), F.count("*").alias("n")) for t in TABLES]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


_SUMS = "SELECT worker_id, split, count(*) AS n, " + ", ".join(f"round(sum(x{i}), 5) + 0.0::DOUBLE AS s{i}" for i in range(D))
QUERIES = {"src_formats": formats, "src_pruned_shards": pruned_shards, "src_run_store": run_store, "src_tables": tables}
ORACLES = {
    "src_formats": f"WITH {CHARGE.strip()} {_SUMS}, fmt FROM charge, (VALUES ('csv'), ('json'), ('orc')) f(fmt) GROUP BY worker_id, split, fmt",
    "src_pruned_shards": f"WITH {CHARGE.strip()} {_SUMS} FROM charge WHERE worker_id IN {PICKED} GROUP BY worker_id, split",
    "src_run_store": f"SELECT * FROM (VALUES ('gd', 4::BIGINT, 4::INTEGER, {3 * 64 * D * 11}::BIGINT), ('sag', 5, 5, {4 * 128 * D})) v(run_id, n, k, bits)",
    "src_tables": " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()),
}
