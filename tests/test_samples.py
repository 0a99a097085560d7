"""Samples in the least space, read once for all runs, and held by threads."""

from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pytest

from fewbit.operators import metrics, objective, tasks
from fewbit.plans import engines
from fewbit.plans.config import Config
from fewbit.plans.driver import Run, fit_many, reference_optimum
from fewbit.queries import workloads


def _rows(df):
    return sorted(map(tuple, df.collect()))


@pytest.mark.parametrize("task, d", [("charge", 9), ("language", tasks.BUCKETS)])
def test_samples_give_what_the_rows_give(spark, sf, task, d):
    rows, own = tasks.TASKS[task][0](spark, sf).persist(), tasks.samples(spark, sf, task).persist()
    twice = own.union(own).withColumn("weight", engines.F.lit(3)) if "weight" not in own.columns else own
    models = {"m": {1: np.linspace(-1, 1, d)}}
    assert _rows(metrics.confusion(rows, models, d)) == _rows(metrics.confusion(own, models, d))
    a, b = objective.geometry(rows, 0.1), objective.geometry(own, 0.1)
    assert np.isclose(a.average, b.average) and np.isclose(a.worst, b.worst)
    assert np.isclose(objective.geometry(twice, 0.1).average, a.average)
    runs = [Run("qavrm_adaptive_plus", Config(rounds=1, steps=2)), Run("q_gd", Config(rounds=1, steps=2))]
    want = fit_many(rows, runs, d, "held")
    for engine in ("rounds", "measured"):
        made = fit_many(own, runs, d, engine, optimum=engine == "measured")
        for x, y in zip(made.trace_rows(), want.trace_rows(), strict=True):
            assert np.isclose(x[5], y[5]) and np.isclose(x[6], y[6])
    assert np.isclose(made.optimum[1], reference_optimum(rows, d, engine="held")[1])


def test_counts_are_held_in_four_bytes(spark, sf, monkeypatch):
    own = tasks.samples(spark, sf, "language").persist()
    cells = own.selectExpr("sum(size(idx))").first()[0]
    assert engines._bytes(own, tasks.BUCKETS)[1] == 4 * cells
    monkeypatch.setattr(engines, "TASK_LIMIT", 4 * cells)
    assert fit_many(own, [Run("gd", Config(rounds=1))], tasks.BUCKETS, "measured").engine == "held"
    many = own.withColumn("n", engines.F.expr("transform(n, v -> v + 70000)"))
    assert engines._bytes(many, tasks.BUCKETS)[1] == 8 * cells
    own.unpersist()


def test_threads_add_the_same_sums_in_the_same_order(monkeypatch):
    monkeypatch.setattr(engines, "THREAD_ROWS", 7)
    draw = np.random.default_rng(1)
    shards = [engines.Shard(3, [(draw.integers(0, 2, n), draw.integers(1, 4, n).astype(float), draw.normal(size=(n, 3)))]) for n in (50, 1, 20)]
    models, one = draw.normal(size=(2, 3)), np.ones(2)
    plain = engines._Held(shards, [0, 1, 2], "logistic").full(models, one, one)
    with ThreadPoolExecutor(4) as pool:
        threads = engines._Held(shards, [0, 1, 2], "logistic", pool.map).full(models, one, one)
    for a, b in zip(plain, threads, strict=True):
        assert (a == b).all()


@pytest.mark.parametrize("name, make", [("w11_memory", "charge_wide")])
def test_a_table_is_made_into_samples_once(spark, sf, monkeypatch, name, make):
    was, calls = getattr(tasks, make), []
    monkeypatch.setattr(tasks, make, lambda *a, **k: calls.append(a) or was(*a, **k))
    monkeypatch.setattr(workloads, "ROUNDS", 1)
    assert workloads.QUERIES[name](spark, sf).count() > 0
    assert len(calls) == 1


def _shards(d, sizes, seed=1):
    draw = np.random.default_rng(seed)
    return [engines.Shard(d, [(draw.integers(0, 2, n), draw.integers(1, 4, n).astype(float), draw.normal(size=(n, d)))]) for n in sizes]


def test_forks_give_the_same_sums_and_end(monkeypatch):
    monkeypatch.setattr(engines, "ALONE", 0)
    monkeypatch.setattr(engines, "DENSE_ROWS", 16)
    shards = _shards(3, (500, 1, 200))
    # equal models are summed up once
    models, one, lam = np.array([[0.1, 2, -3], [1, 1, 1], [0.1, 2, -3]]), np.ones(3), np.full(3, 0.1)
    at = engines._Held(shards, [0, 1, 2], "logistic")
    plain = at.full(models, one, lam)
    at.fork(3)
    pids = [pid for _, pid in at.forks.ends]
    forked = at.full(models, one, lam)
    at.join()
    assert all(np.allclose(a, b, rtol=1e-13, atol=1e-15) for a, b in zip(plain, forked, strict=True))
    for pid in pids:
        with pytest.raises(ChildProcessError):
            engines.os.waitpid(pid, engines.os.WNOHANG)


@pytest.mark.parametrize("size", [1, 600, 3000])
def test_logistic_sums_are_those_of_the_plain_formula(size):
    draw = np.random.default_rng(size)
    x, models, cls = draw.normal(size=(size, 4)) * 20, draw.normal(size=(3, 4)), draw.integers(0, 3, size)
    weight, factor, positive = draw.integers(1, 5, size).astype(float), draw.random(size) + 0.1, np.array([0, 2, 2])
    for w, f in ((None, None), (weight, factor)):
        v, n = x if f is None else x * f[:, None], np.ones(size) if w is None else w
        y = np.where(cls == positive[:, None], 1.0, -1.0)
        m = y * (models @ v.T)
        loss, pull = (np.logaddexp(0, -m) * n).sum(1), -y * n / (1 + np.exp(m))
        made = objective.sums_of(x, cls, models, positive, "logistic", w, True, f)
        assert np.allclose(made[0], pull @ v) and np.allclose(made[1], loss, rtol=1e-12)
        assert np.allclose(objective.sums_of(x, cls, models, positive, "logistic", w, False, f)[0], pull @ v)


def test_the_first_inner_step_takes_no_pass():
    from fewbit.plans import driver
    from fewbit.plans.methods import METHODS

    at, asked = engines._Held(_shards(3, (50, 40)), [0, 1], "logistic"), []
    was = at._sums
    at._sums = lambda ws, *a, **k: asked.append(len(ws)) or was(ws, *a, **k)
    runs = [Run(m, Config(workers=2, rounds=2, steps=3)) for m in ("avr_memory", "sgd", "sag")]
    states = [driver.State(r, METHODS[r.method], np.zeros(3)) for r in runs]
    driver._epochs(at, states, objective.Geometry(1.0, 1.0, 0.2), 1, 3)
    # a pass over both workers a round and one at the end, and two of the three steps
    assert asked == [2, 1, 1, 2, 1, 1, 2]


def test_counts_are_shared_by_forks_too(spark, sf, monkeypatch):
    own = tasks.samples(spark, sf, "language").where("split = 'train'").persist()

    def alone(at):
        # in the task that holds the samples
        return at.forks is not None and len(at.forks.ends) > 1

    for pts in (own, own.withColumn("val", engines.F.expr("transform(n, v -> scale * v / norm)")).drop("n", "scale", "norm")):
        monkeypatch.setattr(engines, "_cores", lambda spark: 2)
        assert engines.HeldEngine(pts, tasks.BUCKETS).run(alone)
        monkeypatch.setattr(engines, "_cores", lambda spark: 1)
        assert not engines.HeldEngine(pts, tasks.BUCKETS).run(alone)
    own.unpersist()


def test_items_are_merged_before_they_are_features(spark, sf, tmp_path):
    """Also odd ones: nulls, negative zeros, a time of day, an item that comes twice and one that only its key tells from it."""
    items = spark.read.parquet(f"{sf}/lineitem.parquet").limit(300).collect()
    odd = [r.asDict() | c for r, c in zip(items, [{"l_tax": None}, {"l_discount": -0.0}, {"l_discount": 0.0}, {"l_orderkey": None}, {"l_extendedprice": 1e9 / 7}], strict=False)]
    odd += [r.asDict() | {"l_suppkey": r.l_suppkey + i} for i in range(3) for r in items[:50]]
    odd += [items[7].asDict() | {"l_shipdate": items[7].l_shipdate.replace(hour=13, microsecond=5)}]
    schema = spark.read.parquet(f"{sf}/lineitem.parquet").schema
    spark.createDataFrame([tuple(r[c] for c in schema.names) for r in [*map(lambda r: r.asDict(), items), *odd]], schema).write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.read.parquet(f"{sf}/part.parquet").write.parquet(f"{tmp_path}/part.parquet")
    rows = tasks.charge(spark, str(tmp_path)).drop("row_id")
    own = tasks.samples(spark, str(tmp_path), "charge")
    key = lambda r: tuple(map(repr, r))
    assert sorted(map(key, own.collect())) == sorted(map(key, rows.groupBy(*rows.columns).agg(engines.F.count("*").alias("weight")).collect()))
    # grouped by what the features are made of: neither texts nor features are compared
    groups = next(line for line in own._jdf.queryExecution().optimizedPlan().toString().splitlines() if "Aggregate" in line).split("], [")[0]
    assert "l_extendedprice" in groups and "split" not in groups and "x0" not in groups
