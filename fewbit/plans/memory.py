"""The one-slot memory that rejects an epoch whose gradient norm grew."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

TIE = 1e-12


@dataclass(frozen=True)
class Anchor:
    """An anchor with all that its exact gradient pass gave: per-worker gradients, their mean, its norm, the loss."""

    model: np.ndarray
    grads: np.ndarray
    mean: np.ndarray
    norm: float
    loss: float


def step(kept: Anchor | None, candidate: Anchor) -> tuple[Anchor, bool]:
    """The anchor to go on from, and whether it is the candidate. A norm that isn't larger is accepted.

    The same anchor measured again may differ in its last digits, by the order of sums; TIE takes that for equal.
    """
    if kept is None or candidate.norm <= kept.norm * (1 + TIE):
        return candidate, True
    return kept, False
