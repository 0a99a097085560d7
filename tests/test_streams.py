"""Streams over files that come one by one."""

import numpy as np

from fewbit import streaming as st
from fewbit.operators.tasks import sensor_of
from fewbit.plans.config import Config
from fewbit.plans.driver import Run, fit_many
from fewbit.queries import streams
from fewbit.sources import load


def feed(spark, events, path, trainer, checkpoint):
    stream = sensor_of(st.event_stream(spark, path)).drop("ts")
    stream.writeStream.foreachBatch(trainer).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def test_trainer_goes_on_after_a_restart(spark, sf, tmp_path):
    e = load(spark, sf, "events")
    parts = [e.where(f"event_id % 3 = {i}").coalesce(1) for i in range(3)]
    for i, p in enumerate(parts[:2]):
        p.write.parquet(f"{tmp_path}/in/{i}")
    first = st.StreamTrainer(9, path=f"{tmp_path}/state", spark=spark)
    feed(spark, e, f"{tmp_path}/in/*", first, f"{tmp_path}/check")
    parts[2].write.parquet(f"{tmp_path}/in/2")
    again = st.StreamTrainer(9, path=f"{tmp_path}/state", spark=spark)
    assert again.last == 1 and np.array_equal(again.model, first.model) and again.model.any()
    feed(spark, e, f"{tmp_path}/in/*", again, f"{tmp_path}/check")
    assert [t[0] for t in again.trace] == [0, 1, 2] and again.trace[:2] == first.trace
    # the same batches one after the other, without a stream
    model = np.zeros(9)
    for number, p in enumerate(parts):
        pts = sensor_of(p).drop("ts")
        config = Config(workers=pts.select("worker_id").distinct().count(), rounds=1, steps=8, seed=number, start=model.tolist())
        model = fit_many(pts, [Run("qavrm_adaptive_plus", config)], 9, "local").states[0].kept.model
    assert np.allclose(model, again.model, atol=1e-9)
    before = again.model.copy()
    again(sensor_of(parts[0]).drop("ts"), 0)
    assert np.array_equal(before, again.model)


def test_streamed_and_batch_sums_agree(spark, sf, tmp_path):
    e = load(spark, sf, "events").orderBy("ts")
    days = [r[0] for r in e.selectExpr("date_trunc('day', ts) AS d").distinct().orderBy("d").collect()]
    for i, lo in enumerate(days[::10]):
        hi = days[min(10 * i + 10, len(days) - 1)] if 10 * i + 10 < len(days) else None
        part = e.where(e.ts >= lo) if hi is None else e.where((e.ts >= lo) & (e.ts < hi))
        part.coalesce(1).write.parquet(f"{tmp_path}/in/{i}")
    out = st.windowed_sums(st.event_stream(spark, f"{tmp_path}/in/*")).writeStream.format("memory").queryName("fb_test_sums").outputMode("complete")
    out.option("checkpointLocation", f"{tmp_path}/check").trigger(availableNow=True).start().awaitTermination()
    got = {(r.w.start, r.worker_id): (r.n, round(r.s, 6)) for r in spark.table("fb_test_sums").collect()}
    want = e.selectExpr("date_trunc('day', ts) AS d", "int(user_id % 10) AS w", "value").groupBy("d", "w").agg({"value": "sum", "*": "count"}).collect()
    assert got == {(r.d, r.w): (r["count(1)"], round(r["sum(value)"], 6)) for r in want}


def test_results_of_sessions_stay_off_the_driver(spark, sf):
    """The result lies in files; a table in the driver's memory has none."""
    assert streams.session_windows(spark, sf).inputFiles()


def test_unique_events_stay_off_the_driver(spark, sf):
    assert streams.deduplicated(spark, sf).inputFiles()


def test_repeats_are_told_by_state_on_disk(spark, sf, monkeypatch):
    from fewbit.queries import streams

    was, seen, before = streams._each_batch, [], spark.conf.get(streams.PROVIDER, None)
    monkeypatch.setattr(streams, "_each_batch", lambda s, *a: seen.append(s.conf.get(streams.PROVIDER)) or was(s, *a))
    made = streams.deduplicated(spark, sf).collect()
    want = spark.read.parquet(f"{sf}/events.parquet").selectExpr("event_type", "event_id").distinct().groupBy("event_type").count().collect()
    assert sorted(map(tuple, made)) == sorted(map(tuple, want))
    assert seen == [streams.ROCKSDB] and spark.conf.get(streams.PROVIDER, None) == before
