"""Sizes of a sketch: tables, bins, independence, budgets, for the proof and for practice."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

#: Constants that the proof needs (the ones without a published value are re-derived; see README).
C_REP, C_BIN, C_PRE, C_DEV, C_SPACE = 4.0, 9 * 2**23, 32, 30.0, 33.0
#: Independence of the bins, k = ceil(C_K1 ln b + C_K2): engine defaults, checked empirically.
C_K1, C_K2 = 7.5, 16.0
PROOF_OFFSET, PRACTICAL_OFFSET, PRACTICAL_BUDGET = 9, 2, 1.5
#: Bound of the second eigenvalue of the base graph.
BASE_LAMBDA = 5 * math.sqrt(2) / 8


@dataclass(frozen=True)
class SketchParams:
    """l tables of b bins over keys of d bits; ``budget`` is in bits per cell; profile 'proof' or 'practical'."""

    l: int  # noqa: E741
    b: int
    k: int
    d: int = 64
    offset: int = PRACTICAL_OFFSET
    budget: float = PRACTICAL_BUDGET
    profile: str = "practical"
    eps: float | None = None
    delta: float | None = None

    def __post_init__(self) -> None:
        if self.b < 2 or self.b & (self.b - 1):
            raise ValueError("b must be a power of two, at least 2")
        if self.l < 1 or self.k < 2 or not 1 <= self.d <= 256:
            raise ValueError("need l >= 1, k >= 2 and 1 <= d <= 256")
        if not 0 <= self.offset <= self.log_b:
            raise ValueError(f"offset {self.offset} must lie between 0 and ld b = {self.log_b}: beyond it nothing is counted")
        if self.budget <= 0:
            raise ValueError("budget must be positive")

    @property
    def log_b(self) -> int:
        return self.b.bit_length() - 1

    @property
    def pre_bits(self) -> int:
        """Bits of the range between the two steps of the bin map: C_PRE * b * b values."""
        return 5 + 2 * self.log_b

    @property
    def max_level(self) -> int:
        return self.d

    @property
    def space_limit(self) -> int:
        return math.floor(self.budget * self.b * self.l)


def repetitions_for(delta: float) -> int:
    return math.ceil(C_REP * math.log(2 / delta))


def independence(b: int) -> int:
    return math.ceil(C_K1 * math.log(b) + C_K2)


def derive(bits: int, eps: float, delta: float, profile: str = "proof", **practical) -> SketchParams:
    """Sizes for keys of ``bits`` bits, relative accuracy eps and failure probability delta >= 1 / ln(2**bits)."""
    if not 0 < eps < 1 or not 0 < delta < 1:
        raise ValueError("eps and delta must lie between 0 and 1")
    if profile == "proof":
        b = 2 ** math.ceil(math.log2(C_BIN / eps**2))
        return SketchParams(repetitions_for(delta), b, independence(b), bits, PROOF_OFFSET, C_SPACE, "proof", eps, delta)
    b = practical.pop("b", 2 ** max(4, math.ceil(math.log2(16 / eps**2))))
    base = SketchParams(practical.pop("l", repetitions_for(delta)), b, practical.pop("k", independence(b)), bits, profile="practical", eps=eps, delta=delta)
    return replace(base, **practical) if practical else base


def inner_lambda_log(l: int, mode: str = "walk_paper") -> float:  # noqa: E741
    """-ln of the spectral bound for walks of l vertices: the proof's, or 1/16 (enough while the cut cannot move)."""
    return math.log(16) if mode == "walk_16" or l < 2 else max(math.log(16), l * math.log(l) ** 3)


def hop_steps(minus_log_lambda: float) -> int:
    """Steps of the base graph that make one hop of a graph with this spectral bound."""
    return max(1, math.ceil(minus_log_lambda / -math.log(BASE_LAMBDA)))
