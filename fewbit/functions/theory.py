"""Bounds on steps, bits and epoch length, and the rates they give.

L: smoothness, mu: strong convexity, a: step, d: dimension, p: bits per coordinate, T: inner steps, noise: constant of the
lattice-noise term (4 as published; 0.954 gives the published plot).
"""

from __future__ import annotations

import math

NOISE = 4.0


def lattice_noise(L, mu, a, d, p, noise=NOISE) -> float:
    cells = math.inf if p == math.inf else 2.0**p - 1
    return noise * L * d * (1 + 3 * L * L * a * a) / (mu * cells**2)


def step_limit(L) -> float:
    return 1 / (6 * L)


def fixed_epoch_min(L, mu, a) -> float:
    """Least epoch length at which the method with a fixed lattice contracts; infinite where no length does."""
    room = mu * a * (1 - 6 * L * a)
    return 1 / room if room > 0 else math.inf


def fixed_rate(L, mu, a, T) -> float:
    return (1 / (mu * T) + 3 * L * a * a) / (a - 3 * L * a * a)


def fixed_ball(L, mu, a, T, delta, betas) -> float:
    """Level at which a fixed lattice stalls: delta and betas are the mean square rounding errors of gradient and models."""
    return (3 * T * a * a * delta + math.fsum(betas)) / (2 * T * a - 12 * L * T * a * a - 2 / mu)


def model_radius(grad_norm, mu) -> float:
    return 2 * grad_norm / mu


def grad_radius(grad_norm, L, mu) -> float:
    return 2 * L * grad_norm / mu


def _bits(L, mu, a, d, room, noise) -> float:
    if room <= 0:
        return math.inf
    return math.ceil(math.log2(1 + math.sqrt(noise * L * d * (1 + 3 * L * L * a * a) / (mu * mu * a * room))))


def adaptive_bits_min(L, mu, a, d, noise=NOISE) -> float:
    return _bits(L, mu, a, d, 1 - 6 * L * a, noise)


def adaptive_epoch_min(L, mu, a, d, p, noise=NOISE) -> float:
    room = mu * a * (1 - 6 * L * a) - lattice_noise(L, mu, a, d, p, noise)
    return 1 / room if room > 0 else math.inf


def adaptive_rate(L, mu, a, d, p, T, noise=NOISE) -> float:
    return (1 / T + 3 * mu * L * a * a + lattice_noise(L, mu, a, d, p, noise)) / (mu * (a - 3 * L * a * a))


def bits_for_target(target, L, mu, a, d, noise=NOISE) -> float:
    return _bits(L, mu, a, d, target - 3 * L * a * target - 3 * L * a, noise)


def epoch_for_target(target, L, mu, a, d, p, noise=NOISE) -> float:
    """Least epoch length for a contraction of target; infinite outside the feasible steps."""
    room = mu * a * (target - 3 * L * a * target - 3 * L * a) - lattice_noise(L, mu, a, d, p, noise)
    return 1 / room if room > 0 else math.inf


def step_window(target, L, mu, d, p, noise=NOISE) -> tuple[float, float]:
    """Feasible steps of epoch_for_target, an open interval; (nan, nan) if there are none."""
    limit = target / (3 * L * (1 + target))
    if p == math.inf:
        return 0.0, limit
    top = best_step(target, L, mu, d, p, noise)
    if not math.isfinite(epoch_for_target(target, L, mu, top, d, p, noise)):
        return math.nan, math.nan

    def edge(bad, good):
        for _ in range(200):
            mid = (bad + good) / 2
            if math.isfinite(epoch_for_target(target, L, mu, mid, d, p, noise)):
                good = mid
            else:
                bad = mid
        return good

    return edge(0.0, top), edge(limit, top)


def best_step(target, L, mu, d, p, noise=NOISE) -> float:
    """The step that allows the shortest epoch: the vertex of a parabola in a."""
    h = 0.0 if p == math.inf else noise * L * d / (mu * (2.0**p - 1) ** 2)
    return mu * target / (2 * (3 * mu * L * (1 + target) + 3 * L * L * h))


def epoch_best(target, L, mu, d, p, noise=NOISE) -> float:
    """epoch_for_target with the step minimised out."""
    return epoch_for_target(target, L, mu, best_step(target, L, mu, d, p, noise), d, p, noise)


def rounding_variance_cap(radius, p, d) -> float:
    """Most mean square error of the random rounding of a vector inside the hull."""
    return d * radius * radius / (2.0**p - 1) ** 2


def epoch_sql(target: str, L: str, mu: str, a: str, d: str, p: str, noise: float = NOISE) -> str:
    """SQL (Spark and DuckDB alike) for epoch_for_target; null where no epoch length does."""
    h = f"({noise} * {L} * {d} * (1.0 + 3.0 * {L} * {L} * {a} * {a}) / ({mu} * power(power(2.0, {p}) - 1.0, 2)))"
    room = f"({mu} * {a} * ({target} - 3.0 * {L} * {a} * {target} - 3.0 * {L} * {a}) - {h})"
    return f"(CASE WHEN {room} > 0 THEN 1.0 / {room} END)"


def best_step_sql(target: str, L: str, mu: str, d: str, p: str, noise: float = NOISE) -> str:
    h = f"({noise} * {L} * {d} / ({mu} * power(power(2.0, {p}) - 1.0, 2)))"
    return f"({mu} * {target} / (2.0 * (3.0 * {mu} * {L} * (1.0 + {target}) + 3.0 * {L} * {L} * {h})))"
