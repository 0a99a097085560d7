"""Queries do the whole job: no row, coordinate or character of the input is left out."""

import hashlib
import math
from collections import Counter

import pytest

from fewbit.operators import tasks
from fewbit.queries import relational, theory, workloads


def test_trigrams_of_whole_texts(spark, tmp_path):
    n = tasks.STRETCH
    long = "".join(f"wört{i} 😀" for i in range(600))
    texts = ["abc", "ab", long, long, *[long[:k] for k in (n - 1, n, n + 1, n + 2, n + 3, 2 * n + 2, 2 * n + 3)]]
    rows = [(i, t, "en") for i, t in enumerate(texts)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    want = Counter()
    for i, t in enumerate(texts):
        if i != 3:
            want.update((i, int(hashlib.md5(t[k : k + 3].encode()).hexdigest()[:8], 16) % tasks.BUCKETS) for k in range(len(t) - 2))
    assert {(r.doc_id, r.bucket): r.n for r in tasks.language_cells(spark, str(tmp_path)).collect()} == want


def test_every_event_has_an_interval(spark, tmp_path):
    values = [-3.0, 0.0, 9.5, 10.0, 399.9, 400.0, 560.2, float("inf"), float("-inf"), float("nan"), None]
    spark.createDataFrame([(i, v) for i, v in enumerate(values)], "event_id long, value double").write.parquet(f"{tmp_path}/events.parquet")
    got = {r.lo: r.n for r in relational.join_interval(spark, str(tmp_path)).collect()}
    assert got == {float("-inf"): 2, 0.0: 2, 10.0: 1, 390.0: 1, 400.0: 3, None: 2}


def test_every_coordinate_has_a_cell(spark, tmp_path):
    rows = [(0, [-0.9, -0.25, -0.01, 0.01, 0.24, 0.25, 0.9, float("inf")]), (1, [0.1] * 7 + [None])]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    place = lambda v: None if v is None else int(min(max(math.floor(min(v, 1.0) / (0.5 / 15) + 7.5), 0), 14))
    want = Counter((i, place(v)) for _, x in rows for i, v in enumerate(x))
    assert {(r.dim, r.cell): r.n for r in theory.cell_join(spark, str(tmp_path)).collect()} == want


def test_experiments_run_the_published_rounds(spark, monkeypatch):
    ran = []

    def fit_many(pts, runs, d, engine="epoch"):
        ran.append((d, {r.config.rounds for r in runs}, {(r.config.model_bits, r.config.grad_bits) for r in runs}))
        raise InterruptedError

    class Nothing:
        persist = lambda self: self
        where = lambda self, _: self

    for task, (_, d, classes) in workloads.tasks.TASKS.items():
        monkeypatch.setitem(workloads.tasks.TASKS, task, (lambda *_: Nothing(), d, classes))
    monkeypatch.setattr(workloads, "fit_many", fit_many)
    names = [n for n in workloads.QUERIES if n[:3] in ("w03", "w04", "w05", "w06", "w07")]
    for name in names:
        with pytest.raises(InterruptedError):
            workloads.QUERIES[name](spark, "")
    assert all(rounds == {50} for _, rounds, _ in ran) and len(ran) == len(names)
    assert {(d, bits) for d, _, b in ran for bits in b} >= {(9, (3, 3)), (9, (9, 9)), (784, (7, 7)), (784, (10, 10)), (64, (7, 7)), (64, (10, 10))}
