"""The methods as combinations of a family, a lattice policy, a memory and a choice of what is rounded."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Spec:
    """family: gd, sgd, sag or avr (anchored variance-reduced); lattice: None, fixed or adaptive; inner: what an inner
    step rounds beside the model: nothing (exact), the anchor gradient, both gradients, or only the model itself."""

    family: str
    lattice: str | None = None
    memory: bool = False
    inner: str = "exact"
    parent: str = ""


METHODS: dict[str, Spec] = {
    "gd": Spec("gd"),
    "sgd": Spec("sgd"),
    "sag": Spec("sag"),
    "q_gd": Spec("gd", "fixed", parent="gd"),
    "q_sgd": Spec("sgd", "fixed", parent="sgd"),
    "q_sag": Spec("sag", "fixed", parent="sag"),
    "avr": Spec("avr"),
    "avr_memory": Spec("avr", memory=True),
    "qavr_fixed": Spec("avr", "fixed", False, "anchor", "avr"),
    "qavrm_fixed": Spec("avr", "fixed", True, "anchor", "avr_memory"),
    "qavrm_adaptive": Spec("avr", "adaptive", True, "anchor", "avr_memory"),
    "qavrm_fixed_plus": Spec("avr", "fixed", True, "both", "avr_memory"),
    "qavrm_adaptive_plus": Spec("avr", "adaptive", True, "both", "avr_memory"),
    "qavr_adaptive": Spec("avr", "adaptive", False, "anchor", "avr"),
    "qavr_adaptive_plus": Spec("avr", "adaptive", False, "both", "avr"),
    "qavr_model_only": Spec("avr", "adaptive", True, "model", "avr_memory"),
}
