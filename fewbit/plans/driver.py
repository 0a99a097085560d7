"""The one driver of all methods: rounds of exact passes, inner steps, roundings, memory, ledger and trace.

Runs are batched: all runs of a call share their draws of workers and steps, so each pass over the data serves all of
them, and their curves are comparable. State between rounds is a few vectors per run; nothing of the data is kept.
"""

from __future__ import annotations

import json
import math
import time
from collections.abc import Callable, Sequence
from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from fewbit.functions import rng
from fewbit.functions.lattice import EXACT, Lattice
from fewbit.functions.ledger import WORD, Wire, bits_paper
from fewbit.operators.objective import Geometry, geometry
from fewbit.plans import memory
from fewbit.plans.config import Config
from fewbit.plans.engines import ENGINES, Engine
from fewbit.plans.methods import METHODS, Spec

TRACE = (
    "run_id string, method string, cls int, p int, k int, loss double, grad_norm double, accepted boolean, saturated long, "
    "closing boolean, bits_paper long, bits_wire long, cum_bits_paper long, status string"
)
MESSAGES = "run_id string, k int, t int, direction string, kind string, worker_id int, bits long, saturated int, sq_error double, payload binary, travels boolean"
LEDGER = "run_id string, method string, k int, bits_paper long, bits_wire long, cum_bits_paper long"
COSTS = "k int, seconds double, rows_scanned long, bytes_moved long"


@dataclass(frozen=True)
class Run:
    """One method with its settings; cls: the class that counts as +1."""

    method: str
    config: Config
    cls: int = 1
    run_id: str = ""

    @property
    def name(self) -> str:
        return self.run_id or f"{self.method}-p{_bits(self.config.model_bits)}-c{self.cls}-r{self.config.radius_scale:g}-s{self.config.seed}"


def _bits(bits) -> int:
    return int(bits if np.isscalar(bits) else round(float(np.mean(bits))))


@dataclass
class State:
    run: Run
    spec: Spec
    model: np.ndarray
    kept: memory.Anchor | None = None
    fixed: tuple | None = None
    table: np.ndarray | None = None
    filled: np.ndarray | None = None
    rejected: int = 0
    cum: int = 0
    status: str = "running"
    trace: list[tuple] = field(default_factory=list)
    models: list[np.ndarray] = field(default_factory=list)
    messages: list[tuple] = field(default_factory=list)
    keep: bool = False


@dataclass
class Result:
    states: list[State]
    geometry: Geometry
    workers: list[int]
    costs: list[tuple] = field(default_factory=list)
    engine: str = ""
    #: What `reference_optimum` gives, if asked for with the runs.
    optimum: tuple[np.ndarray, float, float] | None = None

    def trace_rows(self) -> list[tuple]:
        return [row for s in self.states for row in s.trace]

    def trace(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.trace_rows(), TRACE)

    def models(self, spark: SparkSession) -> DataFrame:
        rows = [(s.run.name, s.run.method, s.run.cls, k, [float(v) for v in w]) for s in self.states for k, w in enumerate(s.models, 1)]
        return spark.createDataFrame(rows, "run_id string, method string, cls int, k int, w array<double>")

    def messages(self, spark: SparkSession) -> DataFrame:
        """All that was rounded or sent, if the run was asked to keep it; `travels` tells what went over a link."""
        return spark.createDataFrame([m for s in self.states for m in s.messages], MESSAGES)

    def ledger(self, spark: SparkSession) -> DataFrame:
        rows = [(r[0], r[1], r[4], r[10], r[11], r[12]) for r in self.trace_rows()]
        return spark.createDataFrame(rows, LEDGER)

    def cost(self, spark: SparkSession) -> DataFrame:
        """By epoch, for all runs of the batch together: wall time, rows read, bytes of partial sums moved."""
        return spark.createDataFrame(self.costs, COSTS)

    def views(self, spark: SparkSession, pts: DataFrame) -> None:
        """The views pts, models, trace, ledger and messages, for SQL."""
        made = {"pts": pts, "models": self.models(spark), "trace": self.trace(spark), "ledger": self.ledger(spark), "messages": self.messages(spark)}
        for name, df in made.items():
            df.createOrReplaceTempView(name)

    def final(self) -> dict[str, np.ndarray]:
        return {s.run.name: s.kept.model if s.kept is not None and s.spec.memory else s.models[-1] for s in self.states}


class Rounder:
    """Rounds vectors on lattices with the run's draws, and books each message."""

    def __init__(self, config: Config, k: int, keep: bool = False):
        self.config, self.k, self.keep = config, k, keep
        self.wire, self.saturated, self.booked = Wire(), 0, []

    def __call__(self, v: np.ndarray, lattice: Lattice, stream: str, t: int, worker: int = -1, travels: bool = True) -> np.ndarray:
        from fewbit.functions.codec import pack

        key = stream if worker < 0 else f"{stream}{worker}"
        u = 0.5 if self.config.rounding == "nearest" else rng.uniforms(self.config.seed, key, self.k, t, len(v))
        out = lattice.round_random(v, u)
        lost = lattice.saturated(v)
        self.saturated += lost
        way = "down" if stream == "model" else "up"
        if travels:
            self.wire.send(way, stream, lattice.total_bits)
        if self.keep:
            payload = None if lattice.exact.any() else pack(lattice.random_index(v, u).astype(np.int64), lattice.bits)
            self.booked.append((self.k, t, way, stream, worker, lattice.total_bits, lost, float(((out - v) ** 2).sum()), payload, travels))
        return out

    def plain(self, way: str, kind: str, d: int, t: int, workers: Sequence[int] = (-1,)) -> None:
        """A vector sent as it is, by each of the workers."""
        self.wire.send(way, kind, WORD * d, len(workers))
        if self.keep:
            self.booked += [(self.k, t, way, kind, w, WORD * d, 0, 0.0, None, True) for w in workers]


def fit_many(
    pts: DataFrame, runs: Sequence[Run], d: int, engine: str | Engine = "rounds", resume: dict | None = None, on_epoch: Callable | None = None, messages: bool = False, optimum: bool = False
) -> Result:
    """Runs all methods together on the training samples (worker_id, cls, x or idx and val).

    resume: what `snapshot` gave after an epoch; the rest of the run is then what it would have been. on_epoch(k, states)
    is called after each epoch, to keep a snapshot, or the messages of the epoch, which are dropped after it. messages:
    keep each message with its packed bits; what is kept then grows with rounds, steps and dimension. optimum: find that of
    the first run's class and settings as well, on the samples as the engine has them.
    """
    first = runs[0].config
    for r in runs:
        c = r.config
        if (c.seed, c.steps, c.rounds, c.workers, c.objective) != (first.seed, first.steps, first.rounds, first.workers, first.objective):
            raise ValueError("runs of one batch share seed, steps, rounds, workers and objective")
    at = ENGINES[engine](pts, d, first.objective) if isinstance(engine, str) else engine
    if len(at.workers) != first.workers:
        raise ValueError(f"{first.workers} workers are configured, {len(at.workers)} have rows")
    shape = geometry(pts, first.lam, first.weighting, first.objective)
    states = [State(r, METHODS[r.method], np.zeros(d) if r.config.start is None else np.array(r.config.start, float), keep=messages) for r in runs]
    for s in states:
        s.run.config.check(s.run.method, shape.smooth(s.run.config.smoothness))
    begin, costs = _restore(states, resume) if resume else 1, []
    best, descend = None, _descent(shape, d, first.lam, runs[0].cls, first.weighting)
    if on_epoch is None:
        states, costs, best = at.run(lambda a: (*_epochs(a, states, shape, begin, first.rounds + 1), descend(a) if optimum else None))
    else:
        for k in range(begin, first.rounds + 2):
            states, more = at.run(lambda a, k=k, states=states: _epochs(a, states, shape, k, k))
            costs += more
            if k <= first.rounds:
                on_epoch(k, states)
                for s in states:
                    s.messages = []
        best = at.run(descend) if optimum else None
    for s in states:
        if s.status == "running":
            s.status = "done"
    return Result(states, shape, at.workers, costs, at.name, best)


def _epochs(at: Engine, states: list[State], shape: Geometry, begin: int, end: int) -> tuple[list[State], list[tuple]]:
    """Epochs begin to end; the one after the last round is the closing pass."""
    costs, rounds = [], states[0].run.config.rounds
    for k in range(begin, end + 1):
        live = [s for s in states if s.status == "running"]
        if not live:
            break
        since, rows, moved = time.perf_counter(), at.rows, at.moved
        _exact_pass(at, live, shape, k, closing=k > rounds)
        live = [s for s in live if s.status == "running"]
        if live and k <= rounds:
            _inner_steps(at, live, shape, k)
        costs.append((k, time.perf_counter() - since, at.rows - rows, at.moved - moved))
    return states, costs


def _mean(n: np.ndarray, v: np.ndarray, weighting: str) -> np.ndarray:
    """Of values by worker: the mean over workers, or over samples."""
    return v.mean(0) if weighting == "worker" else np.tensordot(n / n.sum(), v, 1)


def _exact_pass(at: Engine, live: list[State], shape: Geometry, k: int, closing: bool = False) -> None:
    models = np.array([s.model for s in live])
    lam = np.array([s.run.config.lam for s in live])
    n, grads, losses = at.full(models, np.array([s.run.cls for s in live]), lam)
    for i, s in enumerate(live):
        c, d = s.run.config, len(s.model)
        mean = _mean(n, grads[:, i], c.weighting)
        now = memory.Anchor(s.model, grads[:, i], mean, float(np.linalg.norm(mean)), float(_mean(n, losses[:, i], c.weighting)))
        finite = math.isfinite(now.norm) and math.isfinite(now.loss)
        accepted = True
        if not finite:
            s.status = "diverged"
        elif s.spec.memory:
            s.kept, accepted = memory.step(s.kept, now)
        else:
            s.kept = now
        s.rejected = 0 if accepted else s.rejected + 1
        if finite:
            s.model = s.kept.model
        if s.fixed is None and finite:
            s.fixed = _fixed_lattices(s, shape)
        paper = 0 if closing else bits_paper(s.run.method, d, len(n), c.steps, _vector_bits(c.model_bits, d), _vector_bits(c.grad_bits, d))
        if closing and s.spec.family == "avr":
            paper = WORD * d * len(n)
        s.cum += paper
        book = Rounder(c, k, s.keep)
        if s.spec.family == "avr":
            book.plain("up", "exact", d, 0, range(len(n)))
        stop = c.stop
        reached = finite and (now.norm <= stop.grad_norm or now.loss <= stop.loss or s.cum >= stop.bits or s.rejected >= stop.rejections or s.kept.norm == 0.0)
        if s.status == "running" and reached and not closing:
            s.status = "stopped" if s.kept.norm > 0 else "converged"
        s.models.append(s.model.copy())
        row = (s.run.name, s.run.method, s.run.cls, _bits(c.model_bits), k, now.loss if finite else None, now.norm if finite else None, accepted, 0, closing, int(paper), 0, int(s.cum), s.status)
        s.trace.append(row)
        _book(s, 0, book.wire.total(), book.booked)


def _vector_bits(bits, d: int) -> int:
    return int(min(bits, WORD) * d) if np.isscalar(bits) else int(np.minimum(bits, WORD).sum())


def _fixed_lattices(s: State, shape: Geometry) -> tuple:
    """(model lattice, gradient lattice of each worker) of the first epoch: the adaptive ones, or as set by the user."""
    c = s.run.config
    if c.radius is not None:
        center = np.zeros(len(s.model)) if c.center is None else np.array(c.center, float)
        return Lattice.of(center, c.radius, c.model_bits), [Lattice.of(np.zeros(len(center)), shape.smooth(c.smoothness) * c.radius, c.grad_bits) for _ in s.kept.grads]
    return _adaptive(s, shape)


def _adaptive(s: State, shape: Geometry) -> tuple:
    c, a = s.run.config, s.kept
    smooth = shape.smooth(c.smoothness)
    return (
        Lattice.adaptive_model(a.model, a.norm, shape.mu, c.model_bits, c.radius_scale),
        [Lattice.adaptive_grad(g, a.norm, smooth, shape.mu, c.grad_bits, c.radius_scale) for g in a.grads],
    )


def _inner_steps(at: Engine, live: list[State], shape: Geometry, k: int) -> None:
    c0 = live[0].run.config
    n_workers = len(at.workers)
    steps = c0.steps if any(s.spec.family == "avr" for s in live) else 1
    drawn = [rng.worker(c0.seed, k, t, n_workers) for t in range(1, steps + 1)]
    avr = [s for s in live if s.spec.family == "avr"]
    single = [s for s in live if s.spec.family in ("sgd", "sag")]
    lattices = {id(s): (s.fixed if s.spec.lattice == "fixed" else _adaptive(s, shape) if s.spec.lattice == "adaptive" else None) for s in live}

    for s in live:
        if s.spec.family == "gd":
            _gd_step(s, lattices[id(s)], k)
    if not avr and not single:
        return
    # the only gradient that a single step takes may be known from the exact pass
    reuse = at.reuses
    passed = avr if reuse else avr + single
    runs = [s.run for s in passed]
    jobs = [
        {"spec": s.spec, "config": s.run.config, "model": s.model, "anchor": s.kept, "lattices": lattices[id(s)], "avr": s.spec.family == "avr", "keep": s.keep}
        for s in passed
    ]

    def steps_of(gradient) -> list:
        return run_steps(jobs, gradient, drawn, k, reuse)

    positive, lam = np.array([r.cls for r in runs]), np.array([r.config.lam for r in runs])
    outs = at.inner(drawn, positive, lam, steps_of) if jobs else []
    if reuse:
        outs += [{"grad": s.kept.grads[drawn[0]]} for s in single]
    for s, out in zip(avr + single, outs, strict=True):
        if s.spec.family == "avr":
            s.model = _picked(s.run.config, out["iterates"], k)
        else:
            _single_step(s, out["grad"], drawn[0], lattices[id(s)], k, n_workers, out)
        _book(s, out["saturated"], out["bits"], out["messages"])


def run_steps(jobs: list[dict], gradient, drawn: list[int], k: int, reuse: bool = False) -> list[dict]:
    """All inner steps of an epoch for a batch of runs; gradient(worker, models) serves all runs at once.

    reuse: the first step is taken at the anchor, whose gradients by worker are known, so no pass is made for it.
    """
    outs = [{"iterates": [j["model"]], "saturated": 0, "bits": 0, "messages": []} for j in jobs]
    for t, w in enumerate(drawn, 1):
        if reuse and t == 1:
            grads = [j["anchor"].grads[w] for j in jobs]
        else:
            models = np.array([o["iterates"][-1] if j["avr"] else j["model"] for j, o in zip(jobs, outs, strict=True)])
            grads = gradient(w, models)
        for j, o, g in zip(jobs, outs, grads, strict=True):
            if not j["avr"]:
                if t == 1:
                    o["grad"] = g
                continue
            c, spec, anchor, lat = j["config"], j["spec"], j["anchor"], j["lattices"]
            d, book = len(g), Rounder(c, k, j["keep"])
            old = anchor.grads[w]
            if lat and spec.inner in ("anchor", "both"):
                # the master made this gradient's lattice from its exact copy, so it need not travel again
                if not c.exact_anchor:
                    old = book(old, lat[1][w], "anchorgrad", t, w, travels=False)
                if spec.inner == "both":
                    g = book(g, lat[1][w], "grad", t, w)
                else:
                    book.plain("up", "grad", d, t, [w])
            else:
                book.plain("up", "grad", d, t, [w])
            moved = o["iterates"][-1] - c.step_at(k) * (g - old + anchor.mean)
            if lat:
                moved = book(moved, lat[0], "model", t)
            else:
                book.plain("down", "model", d, t)
            o["iterates"].append(moved)
            o["saturated"] += book.saturated
            o["bits"] += book.wire.total()
            o["messages"] += book.booked
    return outs


def _picked(c: Config, iterates: list[np.ndarray], k: int) -> np.ndarray:
    if c.pick == "last":
        return iterates[-1]
    if c.pick == "mean":
        return np.mean(iterates[:-1], axis=0)
    return iterates[rng.pick(c.seed, k, len(iterates) - 1)]


def _gd_step(s: State, lattices, k: int) -> None:
    c, d, book = s.run.config, len(s.model), Rounder(s.run.config, k, s.keep)
    if lattices:
        grads = np.array([book(g, lat, "grad", 1, w) for w, (g, lat) in enumerate(zip(s.kept.grads, lattices[1], strict=True))])
        s.model = book(s.model - c.step_at(k) * grads.mean(0), lattices[0], "model", 1)
    else:
        s.model = s.model - c.step_at(k) * s.kept.mean
        book.plain("up", "grad", d, 1, range(len(s.kept.grads)))
        book.plain("down", "model", d, 1)
    _book(s, book.saturated, book.wire.total(), book.booked)


def _single_step(s: State, g: np.ndarray, w: int, lattices, k: int, workers: int, out: dict) -> None:
    """One update of the stochastic or the averaged gradient method with worker w's gradient."""
    c, d, book = s.run.config, len(g), Rounder(s.run.config, k, s.keep)
    if lattices:
        g = book(g, lattices[1][w], "grad", 1, w)
    else:
        book.plain("up", "grad", d, 1, [w])
    move = g
    if s.spec.family == "sag":
        if s.table is None:
            s.table = s.kept.grads.copy() if c.sag_warm else np.zeros((workers, d))
        s.table[w] = g
        move = s.table.mean(0)
    s.model = s.model - c.step_at(k) * move
    if lattices:
        s.model = book(s.model, lattices[0], "model", 1)
    else:
        book.plain("down", "model", d, 1)
    out["saturated"], out["bits"], out["messages"] = book.saturated, book.wire.total(), book.booked


def _book(s: State, saturated: int, bits: int, messages: list) -> None:
    row = list(s.trace[-1])
    row[8] += int(saturated)
    row[11] += int(bits)
    s.trace[-1] = tuple(row)
    s.messages += [(s.run.name, *m) for m in messages]


def snapshot(k: int, states: list[State]) -> dict:
    """All that a run needs to go on after epoch k, as plain values for a JSON file or a one-row table."""

    def anchor(a):
        return None if a is None else {"model": a.model.tolist(), "grads": a.grads.tolist(), "mean": a.mean.tolist(), "norm": a.norm, "loss": a.loss}

    def lattice(x):
        return {"c": x.center.tolist(), "r": x.radius.tolist(), "b": x.bits.tolist()}

    own = [
        {
            "run_id": s.run.name, "model": s.model.tolist(), "kept": anchor(s.kept), "table": None if s.table is None else s.table.tolist(),
            "fixed": None if s.fixed is None else [lattice(s.fixed[0]), [lattice(g) for g in s.fixed[1]]],
            "rejected": s.rejected, "cum": s.cum, "status": s.status, "trace": s.trace, "models": [m.tolist() for m in s.models],
        }
        for s in states
    ]
    return json.loads(json.dumps({"k": k, "states": own}))


def _restore(states: list[State], kept: dict) -> int:
    for s, was in zip(states, kept["states"], strict=True):
        if s.run.name != was["run_id"]:
            raise ValueError("the snapshot is of other runs")
        s.model = np.array(was["model"])
        if was["kept"]:
            a = was["kept"]
            s.kept = memory.Anchor(np.array(a["model"]), np.array(a["grads"]), np.array(a["mean"]), a["norm"], a["loss"])
        s.table = None if was["table"] is None else np.array(was["table"])
        if was["fixed"]:
            make = lambda x: Lattice(np.array(x["c"]), np.array(x["r"]), np.array(x["b"]))
            s.fixed = (make(was["fixed"][0]), [make(g) for g in was["fixed"][1]])
        s.rejected, s.cum, s.status = was["rejected"], was["cum"], was["status"]
        s.trace, s.models = [tuple(r) for r in was["trace"]], [np.array(m) for m in was["models"]]
    return kept["k"] + 1


def fit(pts: DataFrame, method: str, config: Config, d: int, engine: str = "rounds", cls: int = 1) -> Result:
    return fit_many(pts, [Run(method, config, cls)], d, engine)


def reference_optimum(
    pts: DataFrame, d: int, lam: float = 0.1, cls: int = 1, engine: str = "rounds", weighting: str = "worker", tol: float = 1e-10, most: int = 400, objective: str = "logistic"
) -> tuple[np.ndarray, float, float]:
    """(model, loss, gradient norm) of the optimum, by plain descent with step 1/L and Nesterov's momentum for strong convexity."""
    return ENGINES[engine](pts, d, objective).run(_descent(geometry(pts, lam, weighting, objective), d, lam, cls, weighting, tol, most))


def _descent(shape: Geometry, d: int, lam: float, cls: int, weighting: str, tol: float = 1e-10, most: int = 400) -> Callable:
    ratio = (math.sqrt(shape.average) - math.sqrt(shape.mu)) / (math.sqrt(shape.average) + math.sqrt(shape.mu))

    def descend(at: Engine) -> tuple[np.ndarray, float, float]:
        w = v = np.zeros(d)
        loss = norm = math.inf
        for _ in range(most):
            n, g, s = at.full(np.array([v]), np.array([cls]), np.array([lam]))
            mean, loss = _mean(n, g[:, 0], weighting), float(_mean(n, s[:, 0], weighting))
            norm = float(np.linalg.norm(mean))
            if norm <= tol:
                break
            after = v - mean / shape.average
            w, v = after, after + ratio * (after - w)
        return v, loss, norm

    return descend


def with_bits(config: Config, p: int) -> Config:
    return replace(config, model_bits=p, grad_bits=p)


__all__ = ["EXACT", "Config", "Result", "Run", "fit", "fit_many", "reference_optimum", "snapshot", "with_bits"]
