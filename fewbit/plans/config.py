"""Settings of a run."""

from __future__ import annotations

import math
import warnings
from collections.abc import Callable, Sequence
from dataclasses import dataclass, field

from fewbit.operators.objective import OBJECTIVES
from fewbit.plans.methods import METHODS


@dataclass(frozen=True)
class Stop:
    """Ends a run early: at a gradient norm, a loss, a total of bits, or a number of rejected epochs in a row."""

    grad_norm: float = 0.0
    loss: float = -math.inf
    bits: float = math.inf
    rejections: int = 1 << 30


@dataclass(frozen=True)
class Config:
    """workers N, rounds K, steps T, step a (number, list by round, or function of the round), ridge weight lam, bits per
    coordinate of model and gradient, and the choices that the methods leave open."""

    workers: int = 10
    rounds: int = 10
    steps: int = 8
    step: float | Sequence[float] | Callable[[int], float] = 0.2
    lam: float = 0.1
    model_bits: int | Sequence[int] = 9
    grad_bits: int | Sequence[int] = 9
    seed: int = 42
    weighting: str = "worker"
    smoothness: str = "average"
    radius_scale: float = 1.0
    pick: str = "uniform"
    rounding: str = "random"
    exact_anchor: bool = False
    sag_warm: bool = False
    center: Sequence[float] | None = None
    radius: float | None = None
    start: Sequence[float] | None = None
    objective: str = "logistic"
    stop: Stop = field(default_factory=Stop)

    def step_at(self, k: int) -> float:
        if callable(self.step):
            return float(self.step(k))
        if isinstance(self.step, Sequence):
            return float(self.step[min(k, len(self.step)) - 1])
        return float(self.step)

    def check(self, method: str, smooth: float | None = None) -> None:
        if method not in METHODS:
            raise ValueError(f"no method {method!r}; there are {', '.join(METHODS)}")
        if self.workers < 1 or self.steps < 1 or self.rounds < 0 or self.lam <= 0:
            raise ValueError("workers and steps must be at least 1, rounds not negative, lam positive")
        if self.weighting not in ("worker", "sample") or self.smoothness not in ("average", "worst_worker"):
            raise ValueError("weighting is worker or sample, smoothness average or worst_worker")
        if self.objective not in OBJECTIVES:
            raise ValueError(f"objective is one of {', '.join(OBJECTIVES)}")
        if self.pick not in ("uniform", "last", "mean") or self.rounding not in ("random", "nearest"):
            raise ValueError("pick is uniform, last or mean, rounding random or nearest")
        if METHODS[method].family == "avr" and self.steps == 1 and self.pick == "uniform":
            warnings.warn("with one inner step the pick is always the anchor: the run stands still", stacklevel=2)
        if smooth is not None and METHODS[method].family == "avr" and self.step_at(1) >= 1 / (6 * smooth):
            # sufficient only; runs beyond it often do well
            warnings.warn(f"step {self.step_at(1):g} is beyond {1 / (6 * smooth):.4g}, up to which the bounds hold", stacklevel=2)
