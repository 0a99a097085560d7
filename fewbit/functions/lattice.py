"""Finite lattices and the projections on them.

Coordinate i has 2**bits[i] evenly spaced values from center - radius to center + radius, both ends included. Values
outside are clamped first. Bits of 53 and more stand for no rounding.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

import numpy as np

EXACT = 53


@dataclass(frozen=True)
class Lattice:
    center: np.ndarray
    radius: np.ndarray
    bits: np.ndarray

    def __post_init__(self):
        if not len(self.center) == len(self.radius) == len(self.bits):
            raise ValueError("center, radius and bits differ in length")
        if (self.radius < 0).any() or (self.bits < 1).any():
            raise ValueError("radius must not be negative and bits at least 1")

    @classmethod
    def of(cls, center, radius, bits) -> Lattice:
        """radius and bits may be scalars, the same for all coordinates."""
        c = np.asarray(center, float)
        return cls(c, np.broadcast_to(np.asarray(radius, float), c.shape), np.broadcast_to(np.asarray(bits, int), c.shape))

    @classmethod
    def adaptive_model(cls, anchor, grad_norm: float, mu: float, bits, scale: float = 1.0) -> Lattice:
        """Around the anchor, wide enough for the next anchor if its gradient isn't larger."""
        return cls.of(anchor, scale * 2 * grad_norm / mu, bits)

    @classmethod
    def adaptive_grad(cls, anchor_grad, grad_norm: float, smooth: float, mu: float, bits, scale: float = 1.0) -> Lattice:
        """Around a worker's gradient at the anchor."""
        return cls.of(anchor_grad, scale * 2 * smooth * grad_norm / mu, bits)

    @cached_property
    def exact(self) -> np.ndarray:
        return self.bits >= EXACT

    @cached_property
    def top(self) -> np.ndarray:
        """Largest index of each coordinate."""
        return np.exp2(np.minimum(self.bits, EXACT - 1)) - 1

    @cached_property
    def spacing(self) -> np.ndarray:
        return 2 * self.radius / self.top

    @cached_property
    def low(self) -> np.ndarray:
        return self.center - self.radius

    @cached_property
    def plain(self) -> bool:
        """Every coordinate has several values and is rounded."""
        return not self.exact.any() and bool((self.spacing > 0).all())

    @cached_property
    def reach(self) -> np.ndarray:
        """How far from the center a coordinate is still within the hull."""
        return self.radius + 1e-12 * np.maximum(1.0, np.abs(self.center) + self.radius)

    @cached_property
    def total_bits(self) -> int:
        return int(np.minimum(self.bits, 64).sum())

    def position(self, v) -> np.ndarray:
        """Place of v in units of the spacing from the lower end, clamped to the lattice."""
        gap = np.where(self.spacing > 0, self.spacing, 1.0)
        return np.where(self.spacing > 0, np.clip((np.asarray(v, float) - (self.center - self.radius)) / gap, 0, self.top), 0)

    def values(self, index) -> np.ndarray:
        return np.where(self.radius > 0, self.center - self.radius + self.spacing * index, self.center)

    def saturated(self, v) -> int:
        """Coordinates outside the lattice's hull."""
        out = np.abs(np.asarray(v, float) - self.center) > self.reach
        return int(np.count_nonzero(out if self.plain else ~self.exact & out))

    def random_index(self, v, u) -> np.ndarray:
        """Index of the value below, or of the one above with the probability that keeps the mean."""
        return np.minimum(np.floor(self.position(v) + u), self.top)

    def round_random(self, v, u) -> np.ndarray:
        if self.plain:
            # the same arithmetic in place, without what only exact or single-valued coordinates need
            at = np.subtract(v, self.low)
            at /= self.spacing
            np.minimum(np.maximum(at, 0, out=at), self.top, out=at)
            at += u
            np.minimum(np.floor(at, out=at), self.top, out=at)
            at *= self.spacing
            at += self.low
            return at
        return np.where(self.exact, v, self.values(self.random_index(v, u)))

    def round_nearest(self, v) -> np.ndarray:
        return self.round_random(v, 0.5)

    def points(self, coord: int) -> np.ndarray:
        return self.values_of(coord, np.arange(int(self.top[coord]) + 1))

    def values_of(self, coord: int, index: np.ndarray) -> np.ndarray:
        return self.center[coord] - self.radius[coord] + self.spacing[coord] * index


def round_sql(x: str, c: str, r: str, p: str, u: str) -> str:
    """SQL (Spark and DuckDB alike) for the random rounding of one coordinate; u = 0.5 gives the nearest value."""
    top = f"(power(2.0, {p}) - 1.0)"
    step = f"(2.0 * ({r}) / {top})"
    place = f"least(greatest((({x}) - (({c}) - ({r}))) / {step}, 0.0), {top})"
    return f"(CASE WHEN ({r}) > 0 THEN ({c}) - ({r}) + {step} * least(floor({place} + ({u})), {top}) ELSE ({c}) END)"
