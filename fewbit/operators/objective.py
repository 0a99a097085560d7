"""Objectives (ridge logistic loss, ridge least squares), their per-worker gradients and geometry, in four plans with one answer.

wide: scalar columns inside code generation; arrow: matrix products over Arrow batches, many models at once; long: one
row per coordinate, for checks; summarizer: the JVM's weighted vector sum. In each, a task sums what it has read before
anything is shuffled, so the shuffle carries one row per task, worker and model.
"""

from __future__ import annotations

import threading
from collections.abc import Iterator
from dataclasses import dataclass
from typing import Protocol

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

ROWS = 8192
#: Partial rows by worker that a pass sends to the driver as they are; more partitions than this are summed by a shuffle first.
DIRECT = 64


@dataclass(frozen=True)
class Geometry:
    """Smoothness of the mean, of the worst worker, and strong convexity."""

    average: float
    worst: float
    mu: float

    def smooth(self, kind: str) -> float:
        return self.worst if kind == "worst_worker" else self.average


#: How the features of a sample may come: dense, sparse, or sparse as counts, of which each stands for scale * n / norm.
FORMS = (["x"], ["idx", "val"], ["idx", "n", "scale", "norm"])


def columns_of(pts: DataFrame) -> list[str]:
    """worker_id, cls, the features, and the weight if samples stand for several rows."""
    form = next(f for f in FORMS if set(f) <= set(pts.columns))
    return ["worker_id", "cls", *form, *(["weight"] if "weight" in pts.columns else [])]


def matrix(batch: pa.RecordBatch, d: int) -> np.ndarray:
    """Feature rows of a batch of the columns that `columns_of` names."""
    n, names = batch.num_rows, batch.schema.names
    if "idx" not in names:
        flat = batch.column(2).flatten().to_numpy(zero_copy_only=False)
        if len(flat) != n * d:
            raise ValueError(f"samples must all have {d} features")
        return flat.reshape(n, d)
    out = np.zeros((n, d))
    owner = np.repeat(np.arange(n), np.diff(batch.column(2).offsets.to_numpy()))
    value = batch.column(3).flatten().to_numpy()
    if "norm" in names:
        value = batch.column(4).to_numpy()[owner] * value / batch.column(5).to_numpy()[owner]
    out[owner, batch.column(2).flatten().to_numpy()] = value
    return out


def weights(batch: pa.RecordBatch) -> np.ndarray | None:
    """The number of rows that each sample of a batch stands for; None: one."""
    names = batch.schema.names
    return batch.column(names.index("weight")).to_numpy().astype(float) if "weight" in names else None


class Objective(Protocol):
    """A mean over samples of a convex loss of the signed margin or score, plus the ridge term that all objectives share."""

    #: Largest second derivative of the loss by the score.
    curvature: float

    def sums(self, x: np.ndarray, y: np.ndarray, models: np.ndarray, weight: np.ndarray, loss: bool, factor: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
        """Sums over rows, by model: of gradients without the ridge term, and of losses (zeros if not asked for).

        y: signs, models (or 1, for all) x rows. factor: what the features of each row are still to be multiplied by.
        """


#: Factors of 1 to 2 of which a double holds the product.
FACTORS = 512


def scratch(name: str, shape: tuple[int, int]) -> np.ndarray:
    """A thread's own space of that shape, used again: new pages cost as much as the arithmetic."""
    own, size = threading.current_thread().__dict__.setdefault("fewbit_scratch", {}), shape[0] * shape[1]
    if name not in own or own[name].size < size:
        own[name] = np.empty(size)
    return own[name][:size].reshape(shape)


def _log_sums(v: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """Sums over columns of weight * log(v) for v of 1 to 2: one logarithm for up to FACTORS neighbours of equal weight."""
    starts = np.arange(0, v.shape[1], FACTORS)
    if len(ends := np.flatnonzero(weight[1:] != weight[:-1])):
        starts = np.unique(np.concatenate([starts, ends + 1]))
    return np.log(np.multiply.reduceat(v, starts, axis=1)) @ weight[starts]


class Logistic:
    curvature = 0.25

    def sums(self, x, y, models, weight, loss, factor):
        m, s = np.matmul(models, x.T, out=scratch("margin", (len(models), len(x)))), np.zeros(len(models))
        if factor is not None:
            m *= factor
        if loss:
            # one exponential serves the loss and its slope: exp(-|m|) never overflows
            e = np.multiply(m, y, out=scratch("other", m.shape))
            s = -(np.minimum(e, 0, out=e) @ weight)
            np.exp(np.copysign(m, -1, out=e), out=e)
            e += 1
            s += _log_sums(e, weight)
            np.reciprocal(e, out=e)
            e -= 0.5
            pull = np.copysign(e, m, out=m)
            pull -= y / 2
        else:
            pull = np.negative(m, out=m)
            with np.errstate(over="ignore"):
                np.exp(pull, out=pull)
            pull += 1
            np.reciprocal(pull, out=pull)
            pull -= y > 0
        pull *= weight if factor is None else weight * factor
        return pull @ x, s


class LeastSquares:
    """Half the squared distance of the score from the label -1 or +1; `least_squares_optimum` has its exact minimum."""

    curvature = 1.0

    def sums(self, x, y, models, weight, loss, factor):
        score = models @ x.T
        off = (score if factor is None else score * factor) - y
        own = off * weight
        return (own if factor is None else own * factor) @ x, (own * off).sum(1) / 2


OBJECTIVES: dict[str, Objective] = {"logistic": Logistic(), "squares": LeastSquares()}
#: Cells of margins that are worked on at a time, so that they stay in a core's cache.
CELLS = 1 << 17


def sums_of(
    x: np.ndarray, cls: np.ndarray, models: np.ndarray, positive: np.ndarray, objective: str = "logistic", weight: np.ndarray | None = None, loss: bool = True,
    factor: np.ndarray | None = None,
) -> tuple[np.ndarray, np.ndarray]:
    """Sums over rows, by model, of gradients without the ridge term and of losses; a row counts `weight` times and its
    features are still to be multiplied by `factor`."""
    g, s = np.zeros(models.shape), np.zeros(len(models))
    own = positive[:1] if (positive == positive[0]).all() else positive
    rows = max(256, CELLS // len(models))
    for lo in range(0, len(cls), rows):
        part = slice(lo, lo + rows)
        y = np.where(cls[part] == own[:, None], 1.0, -1.0)
        more = OBJECTIVES[objective].sums(x[part], y, models, np.ones(y.shape[1]) if weight is None else weight[part], loss, None if factor is None else factor[part])
        g += more[0]
        s += more[1]
    return g, s


Sums = dict[int, tuple[int, np.ndarray, np.ndarray]]


def worker_sums(pts: DataFrame, models: np.ndarray, positive: np.ndarray, objective: str = "logistic", direct: bool = False) -> Sums:
    """{worker: (rows, gradient sums models x d, loss sums)} by the arrow plan.

    What comes back is workers x models x d numbers, whatever the rows. Feature values must be finite. direct: partitions
    are few (DIRECT at most), so their partial rows come to the driver without a shuffle.
    """
    d, r = models.shape[1], len(models)

    def packed(held: dict[int, list]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays(
            [pa.array([int(w) for w in held], pa.int32()), pa.array([v[0] for v in held.values()], pa.int64()), pa.array([v[1] for v in held.values()], pa.list_(pa.float64()))],
            ["worker_id", "n", "s"],
        )

    def added(held: dict[int, list], w: int, n: int, s: np.ndarray) -> None:
        if w in held:
            held[w][0] += n
            held[w][1] += s
        else:
            held[w] = [n, s]

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}
        for batch in batches:
            for lo in range(0, batch.num_rows, ROWS):
                part = batch.slice(lo, ROWS)
                x, cls = matrix(part, d), part.column(1).to_numpy()
                if not np.isfinite(x).all():
                    raise ValueError("a feature isn't finite")
                owners, weight = part.column(0).to_numpy(), weights(part)
                for w in np.unique(owners):
                    some = owners == w
                    own = None if weight is None else weight[some]
                    g, s = sums_of(x[some], cls[some], models, positive, objective, own)
                    added(held, int(w), int(some.sum() if own is None else own.sum()), np.concatenate([g.ravel(), s]))
        if held:
            yield packed(held)

    def total(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}
        for batch in batches:
            for i, (w, n) in enumerate(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)):
                added(held, w, n, batch.column(2)[i].values.to_numpy().copy())
        if held:
            yield packed(held)

    schema = "worker_id int, n long, s array<double>"
    parts = pts.select(*columns_of(pts)).mapInArrow(partial, schema)
    if not direct:
        parts = parts.repartition("worker_id").mapInArrow(total, schema)
    made: dict[int, list] = {}
    for batch in parts.toArrow().to_batches():
        for i, (w, n) in enumerate(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)):
            added(made, w, n, batch.column(2)[i].values.to_numpy().copy())
    return {w: (n, s[: r * d].reshape(r, d), s[r * d :]) for w, (n, s) in made.items()}


def dot(w: str = "w", x: str = "x") -> str:
    return f"aggregate(zip_with({w}, {x}, (a, b) -> a * b), 0D, (s, v) -> s + v)"


def gradients_wide(wide: DataFrame, models: DataFrame, d: int, lam: float) -> DataFrame:
    """(run_id, worker_id, n, loss, g array) from columns x0.. and a broadcast table models(run_id, w array).

    The models come as a broadcast row, not as literals, so that the generated code stays the same from round to round.
    """
    y = F.when(F.col("cls") == 1, 1.0).otherwise(-1.0)
    m = y * sum((F.col(f"x{i}") * F.element_at("w", i + 1) for i in range(1, d)), F.col("x0") * F.element_at("w", 1))
    both = wide.select("worker_id", "cls", *[f"x{i}" for i in range(d)]).crossJoin(F.broadcast(models.select("run_id", "w")))
    rows = both.select("run_id", "worker_id", y.alias("y"), m.alias("m"), *[f"x{i}" for i in range(d)])
    pull = -F.col("y") / (1 + F.exp("m"))
    loss = F.greatest(-F.col("m"), F.lit(0.0)) + F.log1p(F.exp(-F.abs("m")))
    sums = rows.groupBy("run_id", "worker_id").agg(F.count("*").alias("n"), F.avg(loss).alias("loss"), *[F.avg(pull * F.col(f"x{i}")).alias(f"g{i}") for i in range(d)])
    ridge = sums.join(F.broadcast(models.select("run_id", "w")), "run_id")
    return ridge.select(
        "run_id", "worker_id", "n", (F.col("loss") + lam * F.expr(dot("w", "w"))).alias("loss"),
        F.array(*[F.col(f"g{i}") + 2 * lam * F.element_at("w", i + 1) for i in range(d)]).alias("g"),
    )


def gradients_long(pts: DataFrame, models: DataFrame, lam: float) -> DataFrame:
    """(run_id, worker_id, dim, g): one row per coordinate; for checks on small inputs."""
    y = F.when(F.col("cls") == 1, 1.0).otherwise(-1.0)
    rows = pts.select("worker_id", "x", y.alias("y")).crossJoin(F.broadcast(models.select("run_id", "w")))
    coef = rows.select("run_id", "worker_id", "x", "w", (-F.col("y") / (1 + F.exp(F.col("y") * F.expr(dot())))).alias("c"))
    cells = coef.select("run_id", "worker_id", "c", "w", F.posexplode("x").alias("dim", "v"))
    return cells.groupBy("run_id", "worker_id", "dim").agg((F.avg(F.col("c") * F.col("v")) + 2 * lam * F.first(F.expr("w[dim]"))).alias("g"))


def gradients_summarizer(pts: DataFrame, model: np.ndarray, lam: float) -> dict[int, np.ndarray]:
    """{worker: gradient} of one model by the JVM's weighted vector sums."""
    from pyspark.ml.functions import array_to_vector
    from pyspark.ml.stat import Summarizer

    w = "array(" + ",".join(f"{float(v)!r}D" for v in model) + ")"
    y = F.when(F.col("cls") == 1, 1.0).otherwise(-1.0)
    rows = pts.select("worker_id", y.alias("y"), "x").withColumn("m", F.col("y") * F.expr(dot(w)))
    z = rows.select("worker_id", array_to_vector(F.transform("x", lambda v: v * F.col("y"))).alias("z"), (1 / (1 + F.exp("m"))).alias("c"))
    sums = z.groupBy("worker_id").agg(Summarizer.metrics("sum").summary(F.col("z"), F.col("c")).alias("s"), F.count("*").alias("n")).collect()
    return {r.worker_id: -r.s.sum.toArray() / r.n + 2 * lam * np.asarray(model) for r in sums}


def geometry(pts: DataFrame, lam: float, weighting: str = "worker", objective: str = "logistic") -> Geometry:
    """Smoothness and strong convexity from one scan."""
    values, one = next((v, o) for v, o in (("val", "v"), ("x", "v"), ("n", "(scale * v / norm)")) if v in pts.columns)
    square = F.expr(f"aggregate({values}, 0D, (s, v) -> s + {one} * {one})")
    if "weight" in pts.columns:
        per = pts.groupBy("worker_id").agg((F.sum(square * F.col("weight")) / F.sum("weight")).alias("q"), F.sum("weight").alias("n"))
    else:
        per = pts.groupBy("worker_id").agg(F.avg(square).alias("q"), F.count("*").alias("n"))
    r = per.agg(F.avg("q").alias("even"), (F.sum(F.col("q") * F.col("n")) / F.sum("n")).alias("all"), F.max("q").alias("top")).first()
    mean = r["even"] if weighting == "worker" else r["all"]
    bend = OBJECTIVES[objective].curvature
    return Geometry(mean * bend + 2 * lam, r["top"] * bend + 2 * lam, 2 * lam)


def moments(pts: DataFrame, d: int, cls: int = 1) -> DataFrame:
    """(i, j, m): means over workers of the workers' mean products x_i x_j for i <= j, and of x_i y with j = d.

    A task adds up its own products before anything is shuffled: d (d + 3) / 2 numbers a worker, whatever the rows.
    """

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}
        for batch in batches:
            x, owners = matrix(batch, d), batch.column(0).to_numpy()
            both = np.column_stack([x, np.where(batch.column(1).to_numpy() == cls, 1.0, -1.0)])
            for w in np.unique(owners):
                some = owners == w
                n, s = held.get(int(w), (0, 0.0))
                held[int(w)] = (n + int(some.sum()), s + x[some].T @ both[some])
        i, j = np.triu_indices(d, 0, d + 1)
        for w, (n, s) in held.items():
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.full(len(i), w, np.int32)), pa.array(i.astype(np.int32)), pa.array(j.astype(np.int32)), pa.array(np.full(len(i), n)), pa.array(s[i, j])],
                ["worker_id", "i", "j", "n", "s"],
            )

    parts = pts.select(*columns_of(pts)).mapInArrow(partial, "worker_id int, i int, j int, n long, s double")
    own = parts.groupBy("worker_id", "i", "j").agg((F.sum("s") / F.sum("n")).alias("m"))
    return own.groupBy("i", "j").agg(F.avg("m").alias("m"))


def least_squares_optimum(pts: DataFrame, d: int, lam: float, cls: int = 1) -> np.ndarray:
    """The exact minimum of the ridge least squares by its normal equations; d squared numbers reach the driver."""
    gram, pull = np.zeros((d, d)), np.zeros(d)
    for r in moments(pts, d, cls).collect():
        if r.j == d:
            pull[r.i] = r.m
        else:
            gram[r.i, r.j] = gram[r.j, r.i] = r.m
    return np.linalg.solve(gram + 2 * lam * np.eye(d), pull)


def loss_sql(margin: str = "m") -> str:
    """SQL for the stable logistic loss of a signed margin."""
    return f"(greatest(-({margin}), 0.0) + ln(1.0 + exp(-abs({margin}))))"
