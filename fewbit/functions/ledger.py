"""Bits that the links carry: by the published formulas, and by the messages really encoded."""

from __future__ import annotations

from dataclasses import dataclass, field

from fewbit.plans.methods import METHODS

WORD = 64


def bits_paper(method: str, d: int, workers: int, steps: int, model_bits: int, grad_bits: int) -> int:
    """Bits of one iteration, an epoch of the anchored methods or an update of the others; model_bits and grad_bits of a whole vector."""
    spec = METHODS[method]
    if spec.family in ("sgd", "sag"):
        return model_bits + grad_bits if spec.lattice else 2 * WORD * d
    if spec.family == "gd":
        return model_bits + grad_bits * workers if spec.lattice else WORD * d * (1 + workers)
    full = WORD * d * workers
    if not spec.lattice:
        return full + 3 * WORD * d * steps
    if spec.inner == "model":
        return full + (2 * WORD * d + model_bits) * steps
    return full + (WORD * d * (spec.inner == "anchor") + model_bits + grad_bits) * steps


def bits_sql(d: str, n: str, t: str, bw: str, bg: str) -> str:
    """SQL CASE over `method` (Spark and DuckDB alike) for bits_paper."""
    out = []
    for name, spec in METHODS.items():
        if spec.family in ("sgd", "sag"):
            cost = f"{bw} + {bg}" if spec.lattice else f"128 * {d}"
        elif spec.family == "gd":
            cost = f"{bw} + {bg} * {n}" if spec.lattice else f"64 * {d} * (1 + {n})"
        elif not spec.lattice:
            cost = f"64 * {d} * {n} + 192 * {d} * {t}"
        else:
            more = {"model": f"128 * {d} + {bw}", "anchor": f"64 * {d} + {bw} + {bg}", "both": f"{bw} + {bg}"}[spec.inner]
            cost = f"64 * {d} * {n} + ({more}) * {t}"
        out.append(f"WHEN '{name}' THEN {cost}")
    return "CAST(CASE method " + " ".join(out) + " END AS BIGINT)"


@dataclass
class Wire:
    """Messages of one iteration: (direction, kind, bits)."""

    messages: list[tuple[str, str, int]] = field(default_factory=list)

    def send(self, direction: str, kind: str, bits: int, times: int = 1) -> None:
        self.messages += [(direction, kind, int(bits))] * times

    def total(self, direction: str | None = None) -> int:
        return sum(b for way, _, b in self.messages if direction in (None, way))


def compression(method: str, parent: str, d: int, workers: int, steps: int, p: int) -> dict[str, float]:
    """Saved share of one vector's bits, and of a whole iteration's against the unrounded parent's."""
    own = bits_paper(method, d, workers, steps, p * d, p * d)
    return {"message": 1 - p / WORD, "iteration": 1 - own / bits_paper(parent, d, workers, steps, WORD * d, WORD * d)}
