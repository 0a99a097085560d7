"""Where gradients are computed. All engines give the same numbers; they differ in jobs per epoch and in what moves.

rounds: each pass is a Spark job over the rows it needs, so shards may be larger than an executor; on the sharded store an
    inner step reads the folder of its worker alone. The default.
held: the samples fit in one task, which runs all rounds: one job for a whole run. Equal samples may come once, with their
    number; sparse ones are held sparse, but counts as whole rows of two bytes a feature where these are within the limit.
    As the job has no other task, the executor's cores work on them by forked processes; threads would not let the many short
    steps of a pass run side by side.
epoch: the workers of an epoch are known before it starts, so their shards meet in one task that runs its inner steps.
local: rows are collected, for tests and tiny inputs.
measured: equal samples are merged and counted; held if what is left is within its limit, else rounds; the result names the
    one taken.
The engines that hold samples refuse what goes beyond their stated limits.
"""

from __future__ import annotations

import os
import pickle
import re
from collections.abc import Callable, Iterator, Sequence
from functools import cached_property
from multiprocessing import Pipe
from typing import Any, Protocol

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fewbit.operators.objective import DIRECT, columns_of, matrix, scratch, sums_of, weights, worker_sums

LOCAL_LIMIT = 4_000_000
#: Bytes of features, as doubles, that a task of the held and of the epoch engine may hold.
TASK_LIMIT = 1 << 30
#: Bytes of a sparse feature that is held: a double and its place.
SPARSE_BYTES = 12
#: The same of a count and its place, where both are below NARROW, and where not.
COUNT_BYTES = (4, 8)
NARROW = 1 << 16
#: Rows of held sparse samples that are made dense at a time.
DENSE_ROWS = 512
#: Most held rows that a thread works on at a time, most cells of them (of features or margins), and parts that a pass has if
#: they aren't too short for a thread: whatever the threads, the same sums are added in the same order.
THREAD_ROWS, THREAD_CELLS, PARTS = 1 << 16, 1 << 18, 8
#: Passes over fewer cells are left to one thread or process, as handing them out takes longer.
ALONE = 1 << 18
Gradient = Callable[[int, np.ndarray], np.ndarray]
Inner = Callable[[Gradient], list]


class Engine(Protocol):
    name: str
    workers: list[int]
    #: Rows read and bytes of partial sums moved so far.
    rows: int
    moved: int
    #: Whether gradients that the exact pass gave are used again where an epoch needs them, instead of a pass for them.
    reuses: bool

    def full(self, models: np.ndarray, positive: np.ndarray, lam: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(rows of each worker, gradients workers x models x d, losses workers x models)."""

    def inner(self, drawn: list[int], positive: np.ndarray, lam: np.ndarray, run: Inner) -> list:
        """What run returns, given a function (worker, models) -> gradients for the drawn workers."""

    def run(self, work: Callable[[Engine], Any]) -> Any:
        """What work returns, given an engine; where the samples are held by tasks, work runs beside them."""


def _ridge(n, g, s, models, lam):
    return g / n + 2 * lam[:, None] * models, s / n + lam * (models**2).sum(1)


def _sizes(pts: DataFrame) -> dict[int, int]:
    return {r[0]: r[1] for r in pts.groupBy("worker_id").agg(_rows(pts)).collect()}


def _rows(pts: DataFrame) -> Column:
    return F.sum("weight") if "weight" in pts.columns else F.count("*")


def merged(pts: DataFrame) -> DataFrame:
    """Each distinct sample once, with the number of its rows as `weight`: the same sums from fewer rows."""
    return pts.groupBy(*[c for c in columns_of(pts) if c != "weight"]).agg(_rows(pts).alias("weight"))


def _counted(pts: DataFrame, d: int) -> tuple[dict[int, int], int, bool]:
    """(samples of each worker, least bytes that a task needs to hold the features of all, whether counts as whole rows fit)."""
    counts = "norm" in columns_of(pts)
    cells = F.sum(F.size("idx")) if "idx" in pts.columns else F.count("*") * d
    most = F.max(F.array_max("n")) if counts else F.lit(0)
    made = pts.groupBy("worker_id").agg(_rows(pts), cells, most, F.count("*")).collect()
    wide = any((r[3] or 0) >= NARROW for r in made)
    each = COUNT_BYTES[d > NARROW or wide] if counts else SPARSE_BYTES if "idx" in pts.columns else 8
    whole = counts and not wide and 2 * d * sum(r[4] for r in made) <= TASK_LIMIT
    return {r[0]: r[1] for r in made}, each * sum(r[2] for r in made), whole


def _bytes(pts: DataFrame, d: int) -> tuple[dict[int, int], int]:
    """(samples of each worker, bytes that a task needs to hold the features of all), counted."""
    return _counted(pts, d)[:2]


def _cores(spark: SparkSession) -> int:
    """Cores of one executor."""
    sc = spark.sparkContext
    own = re.match(r"local-cluster\[\s*\d+\s*,\s*(\d+)", sc.master)
    if sc.master.startswith("local") and not own:
        return sc.defaultParallelism
    return int(own[1] if own else sc.getConf().get("spark.executor.cores", "1"))


class RoundsEngine:
    name = "rounds"
    reuses = False

    def __init__(self, pts: DataFrame, d: int, objective: str = "logistic", sizes: dict[int, int] | None = None):
        self.pts, self.d, self.objective, self.rows, self.moved = pts, d, objective, 0, 0
        self.sizes = sizes or _sizes(pts)
        self.workers = sorted(self.sizes)

    @cached_property
    def direct(self) -> bool:
        # asked for only where rounds are run: counting the partitions of a grouping runs it
        return self.pts.rdd.getNumPartitions() <= DIRECT

    def _sums(self, pts, models, positive, workers):
        out = worker_sums(pts, models, positive, self.objective, self.direct)
        self.rows += sum(n for n, _, _ in out.values())
        self.moved += 8 * len(workers) * models.size
        return out

    def full(self, models, positive, lam):
        sums = self._sums(self.pts, models, positive, self.workers)
        made = [_ridge(*sums[w], models, lam) for w in self.workers]
        return np.array([sums[w][0] for w in self.workers]), np.array([g for g, _ in made]), np.array([s for _, s in made])

    def shard(self, w: int) -> DataFrame:
        """The rows of one worker: on the sharded store, a filter on the partition column, so other folders aren't read."""
        return self.pts.where(F.col("worker_id") == self.workers[w])

    def inner(self, drawn, positive, lam, run):
        def gradient(w: int, models: np.ndarray) -> np.ndarray:
            n, g, s = self._sums(self.shard(w), models, positive, [w])[self.workers[w]]
            return _ridge(n, g, s, models, lam)[0]

        return run(gradient)

    def run(self, work):
        return work(self)


class Shard:
    """The samples of a worker in memory: dense, whole counts, or sparse as they came, with the number of rows that each
    stands for. Of counts, a row's features are still to be multiplied by `factor`."""

    def __init__(self, d: int, parts: list[tuple]):
        """parts: (classes, weights or None, then x; or x and factors; or sizes, places and values; or those and factors)."""
        self.d = d
        if not parts:
            parts = [(np.zeros(0, np.int32), None, np.zeros((0, d)))]
        self.sparse, self.factor = len(parts[0]) > 4, None
        columns = list(zip(*parts, strict=True))
        parts.clear()
        self.cls = np.concatenate(columns[0])
        weight = None if columns[1][0] is None else np.concatenate(columns[1])
        self.rows = len(self.cls) if weight is None else int(weight.sum())
        self.weight = np.ones(len(self.cls)) if weight is None else weight
        if self.sparse:
            self.ends = np.concatenate([[0], np.cumsum(np.concatenate(columns[2]))])
            self.idx, self.val = np.concatenate(columns[3]), np.concatenate(columns[4])
        else:
            self.x = np.concatenate(columns[2])
        if len(columns) in (4, 6):
            self.factor = np.concatenate(columns[-1])
        elif weight is not None and not self.sparse:
            # neighbours of equal weight share their logarithms
            order = np.argsort(weight, kind="stable")
            self.cls, self.weight, self.x = self.cls[order], weight[order], self.x[order]

    def __iter__(self) -> Iterator[np.ndarray]:
        """Features and classes of dense samples."""
        return iter((self.x, self.cls))

    def blocks(self, lo: int, hi: int) -> Iterator[tuple[np.ndarray, slice]]:
        """(features as doubles, rows) of rows lo to hi; what isn't held so is made so a stretch at a time, in the same space."""
        if not self.sparse and self.x.dtype == np.float64:
            yield self.x[lo:hi], slice(lo, hi)
            return
        for at in range(lo, hi, DENSE_ROWS):
            rows = slice(at, min(at + DENSE_ROWS, hi))
            yield self.dense(rows), rows

    def dense(self, rows: slice) -> np.ndarray:
        x = scratch("features", (rows.stop - rows.start, self.d))
        if not self.sparse:
            x[:] = self.x[rows]
            return x
        ends = self.ends[rows.start : rows.stop + 1]
        x[:], at = 0, slice(ends[0], ends[-1])
        x.reshape(-1)[np.repeat(np.arange(len(x)) * self.d, np.diff(ends)) + self.idx[at]] = self.val[at]
        return x

    def sums(self, lo, hi, models, positive, objective, loss=True):
        g, s = np.zeros(models.shape), np.zeros(len(models))
        for x, rows in self.blocks(lo, hi):
            more = sums_of(x, self.cls[rows], models, positive, objective, self.weight[rows], loss, None if self.factor is None else self.factor[rows])
            g, s = g + more[0], s + more[1]
        return g, s


def _narrow(v: np.ndarray, most: int) -> np.ndarray:
    """Whole numbers in two bytes if none is larger than most and that is below NARROW, else in four."""
    return v.astype(np.uint16 if most < NARROW else np.int32)


def _held(batches: Iterator[pa.RecordBatch], d: int, ids: list[int], whole: bool = False) -> dict[int, Shard]:
    """{worker: samples} of the rows of ids; whole: counts, none of them NARROW or more, become rows of all features."""
    held: dict[int, list] = {i: [] for i in ids}
    for b in batches:
        names = b.schema.names
        cls, owner, weight, more = b.column(1).to_numpy(), b.column(0).to_numpy(), weights(b), []
        if "idx" in names:
            size, at = np.diff(b.column(2).offsets.to_numpy()), b.column(2).flatten().to_numpy()
            value = b.column(3).flatten().to_numpy()
            if not (at.size == 0 or (0 <= at.min() and at.max() < d)):
                raise ValueError(f"samples must all have {d} features")
            if "norm" in names:
                value = _narrow(value, int(value.max(initial=0)))
                scale, norm = (b.column(c).to_numpy() for c in (4, 5))
                if (norm == 0).any():
                    raise ValueError("a norm is zero")
                more = [scale / norm]
            if whole:
                rows = np.zeros((b.num_rows, d), np.uint16)
                rows.reshape(-1)[np.repeat(np.arange(b.num_rows) * d, size) + at] = value
                value = rows
            else:
                at = _narrow(at, d - 1)
        else:
            value = matrix(b, d)
        if not all(np.isfinite(v).all() for v in (value, *more)):
            raise ValueError("a feature isn't finite")
        for i in ids:
            if (some := owner == i).any():
                row, rest = (cls[some], None if weight is None else weight[some]), [m[some] for m in more]
                if "idx" in names and not whole:
                    cells = np.repeat(some, size)
                    held[i].append((*row, size[some], at[cells], value[cells], *rest))
                else:
                    held[i].append((*row, value[some], *rest))
    return {i: Shard(d, held[i]) for i in ids}


def _returned(out: Any) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([cloudpickle.dumps(out)], pa.binary())], ["out"])


class EpochEngine(RoundsEngine):
    name = "epoch"

    def inner(self, drawn, positive, lam, run):
        d, workers, objective = self.d, self.workers, self.objective
        ids = sorted({workers[w] for w in drawn})
        count = sum(self.sizes[i] for i in ids)
        if 8 * d * count > TASK_LIMIT:
            raise ValueError(f"{count} rows of an epoch's workers are beyond the {TASK_LIMIT} bytes of the epoch engine; use rounds")
        self.rows += count
        rows = self.pts.where(F.col("worker_id").isin(*ids)).select(*columns_of(self.pts))

        def all_steps(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            shard = _held(batches, d, ids)
            at = _Held([shard.get(w) for w in workers], workers, objective)
            yield _returned(at.inner(drawn, positive, lam, run))

        return pickle.loads(rows.repartition(1).mapInArrow(all_steps, "out binary").first()[0])


class Forks:
    """Copies of this process that answer call(number of the copy, *asked); what is in memory they share, not copy.

    They end when this one closes its ends of the pipes, or ends itself.
    """

    def __init__(self, count: int, call: Callable):
        self.ends: list[tuple[Any, int]] = []
        for j in range(count):
            mine, other = Pipe()
            if (pid := os.fork()) == 0:
                self._serve(j, call, mine, other)
            other.close()
            self.ends.append((mine, pid))

    def _serve(self, j: int, call: Callable, mine, other) -> None:
        try:
            # ends of earlier copies came along; held open, they would keep those from ending
            for end in (mine, *[e for e, _ in self.ends]):
                end.close()
            while True:
                asked = other.recv()
                try:
                    other.send(call(j, *asked))
                except Exception as wrong:
                    other.send(wrong)
        except (EOFError, OSError):
            pass
        finally:
            os._exit(0)

    def ask(self, *asked) -> list:
        for end, _ in self.ends:
            end.send(asked)
        made = [end.recv() for end, _ in self.ends]
        for m in made:
            if isinstance(m, Exception):
                raise m
        return made

    def close(self) -> None:
        for end, pid in self.ends:
            end.close()
            os.waitpid(pid, 0)
        self.ends = []


class _Held:
    """Gradients of samples in memory."""

    name = "local"
    reuses = True

    def __init__(self, shards: list[Shard], workers: list[int], objective: str, each: Callable = map):
        """each: map, or that of a pool of threads."""
        self.shards, self.workers, self.objective, self.each, self.rows, self.moved = shards, workers, objective, each, 0, 0
        self.forks: Forks | None = None

    def fork(self, count: int) -> None:
        """From now on, and until `join`, that many copies of this process share the passes."""
        if count > 1:
            self.forks = Forks(count, lambda j, *asked: self._parts(*asked, slice(j, None, count)))

    def join(self) -> None:
        if self.forks:
            self.forks.close()
            self.forks = None

    def _parts(self, ws: Sequence[int], models, positive, rows: int, loss: bool, which: slice, each: Callable = map) -> list[list]:
        """[gradient and loss sums] of each of the workers ws over some of their parts of that many rows."""
        parts = [(i, lo) for i, w in enumerate(ws) for lo in range(0, len(self.shards[w].cls), rows)][which]

        def one(part):
            shard = self.shards[ws[part[0]]]
            return shard.sums(part[1], min(part[1] + rows, len(shard.cls)), models, positive, self.objective, loss)

        sums = [[np.zeros(models.shape), np.zeros(len(models))] for _ in ws]
        for (i, _), more in zip(parts, each(one, parts), strict=True):
            sums[i][0] += more[0]
            sums[i][1] += more[1]
        return sums

    def _sums(self, ws, models, positive, lam, loss=True):
        """(gradients, losses) of each of the workers ws."""
        # runs that have come to the same model share its sums
        met: dict[tuple, int] = {}
        same = [met.setdefault((int(c), w.tobytes()), len(met)) for c, w in zip(positive, models, strict=True)]
        first = [same.index(i) for i in range(len(met))]
        own, side = models[first], positive[first]
        total = sum(len(self.shards[w].cls) for w in ws)
        rows = min(THREAD_ROWS, max(DENSE_ROWS, min(THREAD_CELLS // max(own.shape), -(-total // PARTS))))
        alone = total * max(own.shape) < ALONE
        if self.forks and not alone:
            sums, *rest = self.forks.ask(ws, own, side, rows, loss)
            for more in rest:
                for a, b in zip(sums, more, strict=True):
                    a[0] += b[0]
                    a[1] += b[1]
        else:
            sums = self._parts(ws, own, side, rows, loss, slice(None), map if alone else self.each)
        self.rows += sum(self.shards[w].rows for w in ws)
        return [_ridge(self.shards[w].rows, g[same], s[same], models, lam) for w, (g, s) in zip(ws, sums, strict=True)]

    def full(self, models, positive, lam):
        made = self._sums(range(len(self.workers)), models, positive, lam)
        return np.array([s.rows for s in self.shards]), np.array([g for g, _ in made]), np.array([s for _, s in made])

    def inner(self, drawn, positive, lam, run):
        return run(lambda w, models: self._sums([w], models, positive, lam, loss=False)[0][0])

    def run(self, work):
        return work(self)


class HeldEngine(RoundsEngine):
    """A lost executor restarts the job from where it began (the whole run, or an epoch with `on_epoch`); as draws follow
    from their keys, it comes to the same end."""

    name = "held"

    def __init__(self, pts: DataFrame, d: int, objective: str = "logistic", counted: tuple[dict[int, int], int, bool] | None = None):
        """counted: what `_counted` gives."""
        sizes, needed, self.whole = counted or _counted(pts, d)
        super().__init__(pts, d, objective, sizes)
        if needed > TASK_LIMIT and not self.whole:
            raise ValueError(f"{sum(self.sizes.values())} rows are beyond the {TASK_LIMIT} bytes of the held engine; use rounds")

    def run(self, work):
        d, workers, objective, cores, whole_rows = self.d, self.workers, self.objective, _cores(self.pts.sparkSession), self.whole

        def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            shard = _held(batches, d, workers, whole_rows)
            at = _Held([shard[w] for w in workers], workers, objective)
            try:
                at.fork(max(1, min(cores, os.cpu_count() or 1)))
                out = work(at)
            finally:
                at.join()
            yield _returned((out, at.rows))

        laid = self.pts.select(*columns_of(self.pts)).repartition(1)
        # not `first`, which ends the task while its worker still writes
        out, rows = pickle.loads(laid.mapInArrow(whole, "out binary").collect()[0][0])
        self.rows += rows
        return out


class LocalEngine(_Held):
    def __init__(self, pts: DataFrame, d: int, objective: str = "logistic", limit: int = LOCAL_LIMIT):
        rows = pts.select(*columns_of(pts)).limit(limit // d + 1).toArrow()
        if rows.num_rows * d > limit:
            raise ValueError(f"the local engine holds at most {limit} numbers; use rounds")
        ids = sorted(set(rows.column(0).to_pylist()))
        shard = _held(iter(rows.to_batches()), d, ids)
        super().__init__([shard[i] for i in ids], ids, objective)


def measured(pts: DataFrame, d: int, objective: str = "logistic") -> RoundsEngine:
    # sparse samples are hardly ever equal; those with a weight are merged
    own = pts if {"idx", "weight"} & set(pts.columns) else merged(pts)
    counted = _counted(own, d)
    return HeldEngine(own, d, objective, counted) if counted[1] <= TASK_LIMIT or counted[2] else RoundsEngine(pts, d, objective, counted[0])


ENGINES = {"rounds": RoundsEngine, "held": HeldEngine, "epoch": EpochEngine, "local": LocalEngine, "measured": measured}
