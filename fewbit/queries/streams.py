"""Streams run to their end over the event files, as queries."""

from __future__ import annotations

from contextlib import contextmanager

from pyspark.sql import functions as F

from fewbit import streaming as st
from fewbit.operators.tasks import sensor_of
from fewbit.sources import load, remove, remove_at_exit, work_dir


def _source(spark, sf_dir):
    return st.event_stream(spark, f"{sf_dir}/events.parquet*")


def _finish(spark, out, mode):
    """The result of a stream run to its end, kept in the shared folder: no row of it passes the driver.

    Complete mode gives the whole result with every batch, so the last batch's stays; the other modes add theirs up.
    """
    path, kept = work_dir(spark, "result"), []

    def keep(batch, number):
        # a batch that comes again replaces its own rows
        batch.write.mode("overwrite").parquet(f"{path}/{number}")
        old = [n for n in kept if n != number]
        kept[:] = [number] if mode == "complete" else [*old, number]
        for n in old if mode == "complete" else ():
            remove(spark, f"{path}/{n}")

    _each_batch(spark, out, keep, mode)
    remove_at_exit(spark, path)
    return spark.read.schema(out.schema).parquet(*[f"{path}/{n}" for n in kept]) if kept else spark.createDataFrame([], out.schema)


PROVIDER = "spark.sql.streaming.stateStore.providerClass"
ROCKSDB = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


@contextmanager
def _state_on_disk(spark):
    """Streams started within keep their state on local disks, not on the heap: it may have a key for every row."""
    was = spark.conf.get(PROVIDER, None)
    spark.conf.set(PROVIDER, ROCKSDB)
    try:
        yield
    finally:
        if was is None:
            spark.conf.unset(PROVIDER)
        else:
            spark.conf.set(PROVIDER, was)


def _each_batch(spark, stream, call, mode="append"):
    path = work_dir(spark, "stream")
    stream.writeStream.foreachBatch(call).outputMode(mode).option("checkpointLocation", path).trigger(availableNow=True).start().awaitTermination()
    remove(spark, path)


def windows(spark, sf_dir):
    out = _finish(spark, st.windowed_sums(_source(spark, sf_dir)), "complete")
    return out.select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "worker_id", "n", F.round("s", 4).alias("s"))


def sliding(spark, sf_dir):
    out = _finish(spark, st.windowed_sums(_source(spark, sf_dir), slide="12 hours"), "complete")
    return out.groupBy("worker_id").agg(F.sum("n").alias("n"), F.count("*").alias("windows"))


def deduplicated(spark, sf_dir):
    with _state_on_disk(spark):
        out = _finish(spark, st.unique(_source(spark, sf_dir)).select("event_id", "event_type"), "append")
    return out.groupBy("event_type").agg(F.count("*").alias("n"))


def session_windows(spark, sf_dir):
    out = _finish(spark, st.sessions(_source(spark, sf_dir)), "complete")
    return out.groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("n"))


def state(spark, sf_dir):
    out = _finish(spark, st.worker_state(_source(spark, sf_dir)), "update")
    return out.groupBy("worker_id").agg(F.max("n").alias("n"), F.round(F.max_by("mean", "n"), 6).alias("mean"))


def training(spark, sf_dir):
    trainer = st.StreamTrainer(9)
    _each_batch(spark, sensor_of(_source(spark, sf_dir)).drop("ts"), trainer)
    t = spark.createDataFrame(trainer.trace, "batch long, n long, loss double, grad_norm double")
    return t.select("batch", "n", F.round("loss", 6).alias("loss"), F.round("grad_norm", 6).alias("grad_norm"))


def _training_sql() -> str:
    """The first batch is the whole file; its trace is of the zero model, whose loss is ln 2."""
    from fewbit.queries.methods import sensor_features_sql

    x = sensor_features_sql()
    g = ", ".join(f"avg(-y / 2 * ({v})) AS g{i}" for i, v in enumerate(x))
    norm = " + ".join(f"pow(avg(g{i}), 2)" for i in range(len(x)))
    return f"""SELECT 0::BIGINT AS batch, CAST(sum(n) AS BIGINT) AS n, round(ln(2), 6) AS loss, round(sqrt({norm}), 6) AS grad_norm
FROM (SELECT count(*) AS n, {g} FROM (SELECT *, CASE WHEN value > 35 THEN 1.0 ELSE -1.0 END::DOUBLE AS y FROM events) GROUP BY user_id % 10)"""


def _three_batches(spark, sf_dir, path):
    """The later half of the events but for their last day, then that day, then the earlier half, late."""
    e = load(spark, sf_dir, "events")
    ends = e.agg(F.min("ts").alias("a"), F.max("ts").alias("b")).select(
        F.date_trunc("day", F.timestamp_seconds((F.unix_timestamp("a") + F.unix_timestamp("b")) / 2)).alias("half"), F.date_trunc("day", "b").alias("last")
    )
    dated = e.crossJoin(F.broadcast(ends))
    for n, some in enumerate(("ts >= half AND ts < last", "ts >= last", "ts < half")):
        dated.where(some).drop("half", "last").coalesce(1).write.parquet(f"{path}/{n}")
    return st.event_stream(spark, f"{path}/*")


def late_rows(spark, sf_dir):
    """Rows that came, that were late by the watermark, and that the windowed sums hold."""
    path, counter = work_dir(spark, "late"), st.LateRows()
    stream = _three_batches(spark, sf_dir, path)
    _each_batch(spark, stream, counter)
    sums = _finish(spark, st.windowed_sums(stream), "update")
    kept = sums.groupBy("w", "worker_id").agg(F.max("n").alias("n")).agg(F.sum("n")).first()[0]
    remove(spark, path)
    rows = [(sum(n for n, _ in counter.counts.values()), sum(x for _, x in counter.counts.values()), int(kept))]
    return spark.createDataFrame(rows, "total long, late long, kept long")


def appended(spark, sf_dir):
    """Append mode: a window comes out once, when the watermark has passed its end."""
    out = _finish(spark, st.windowed_sums(_source(spark, sf_dir)), "append")
    return out.groupBy("worker_id").agg(F.count("*").alias("windows"), F.sum("n").alias("n"))


def static_join(spark, sf_dir):
    """Events beside a static table of customers, by segment."""
    users = load(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    out = _finish(spark, st.with_model(_source(spark, sf_dir), users, "user_id").groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.sum("value").alias("s")), "complete")
    return out.select("c_mktsegment", "n", F.round("s", 4).alias("s"))


QUERIES = {"st_windows": windows, "st_sliding": sliding, "st_dedup": deduplicated, "st_sessions": session_windows, "st_worker_state": state, "st_training": training, "st_late_rows": late_rows, "st_append": appended, "st_static_join": static_join}
_HALF = "(SELECT date_trunc('day', to_timestamp((floor(epoch(min(ts))) + floor(epoch(max(ts)))) / 2)) AT TIME ZONE 'UTC' FROM events)"
ORACLES = {
    "st_training": _training_sql(),
    "st_late_rows": f"SELECT count(*) AS total, count(*) FILTER (late) AS late, count(*) FILTER (NOT late) AS kept FROM (SELECT ts < {_HALF} AND date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) FROM events WHERE ts < (SELECT date_trunc('day', max(ts)) FROM events)) - INTERVAL 1 HOUR AS late FROM events)",
    "st_append": "SELECT worker_id, count(*) AS windows, CAST(sum(n) AS BIGINT) AS n FROM (SELECT CAST(user_id % 10 AS INTEGER) AS worker_id, date_trunc('day', ts) AS w, count(*) AS n FROM events GROUP BY ALL) WHERE w + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR GROUP BY 1",
    "st_static_join": "SELECT c_mktsegment, count(*) AS n, round(sum(value), 4) AS s FROM events JOIN customer ON user_id = c_custkey GROUP BY 1",
    "st_sliding": "SELECT worker_id, count(*) AS n, count(DISTINCT w) AS windows FROM (SELECT CAST(user_id % 10 AS INTEGER) AS worker_id, unnest([floor(epoch(ts) / 43200)::BIGINT, floor(epoch(ts) / 43200)::BIGINT - 1]) AS w FROM events) GROUP BY 1",
    "st_windows": "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, CAST(user_id % 10 AS INTEGER) AS worker_id, count(*) AS n, round(sum(value), 4) AS s FROM events GROUP BY ALL",
    "st_dedup": "SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY 1",
    "st_worker_state": "SELECT CAST(user_id % 10 AS INTEGER) AS worker_id, count(*) AS n, round(avg(value), 6) AS mean FROM events GROUP BY 1",
    "st_sessions": "WITH m AS (SELECT user_id, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events) SELECT user_id, CAST(sum(new) AS BIGINT) AS sessions, count(*) AS n FROM m GROUP BY 1",
}
