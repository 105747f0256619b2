"""Calculators: tail bounds of expander walks, repetition counts and space formulas."""

from __future__ import annotations

import math

import numpy as np

from .params import C_DEV


def kl(g: float, p: float) -> float:
    """Divergence of Bernoulli(g) from Bernoulli(p)."""
    part = lambda a, b: 0.0 if a == 0 else math.inf if b == 0 else a * math.log(a / b)
    return part(g, p) + part(1 - g, 1 - p)


def kl_lower(g: float, p: float) -> float:
    return g * math.log(1 / p) - 2 / math.e


def tail_kl_2010(mu: float, lam: float, excess: float, length: int) -> float:
    """Older tail bound of a walk's mean exceeding mu + excess; needs 6 lam <= mu and 2 lam < excess < 1."""
    if not (6 * lam <= mu and 2 * lam < excess < 1 and mu + excess <= 1):
        raise ValueError("needs 6 lam <= mu and 2 lam < excess < 1")
    return math.exp(-length * kl(min(1.0, mu + excess - 2 * lam), mu + 2 * lam)) if mu + 2 * lam < mu + excess - 2 * lam else 1.0


def hitting(mu: float, lam: float, visits: int) -> tuple[float, float]:
    """Chance that a walk is in a set of density mu at all of some chosen steps: exact form and the simpler one above it."""
    return (mu * (1 - lam) + lam) ** visits, (mu + lam) ** visits


def tail_kl(mu: float, lam: float, g: float, length: int) -> float:
    """Chance that at least a share g of a walk lies in a set of density mu; needs mu + lam <= g <= 1."""
    if not mu + lam <= g <= 1:
        raise ValueError("needs mu + lam <= g <= 1")
    return math.exp(-length * kl(g, mu + lam))


def tail_log(mu: float, lam: float, g: float, length: int) -> float:
    if not mu + lam <= g <= 1:
        raise ValueError("needs mu + lam <= g <= 1")
    return math.exp(-length * kl_lower(g, mu + lam))


def tail_quadratic(mu: float, lam: float, g: float, length: int) -> float:
    return math.exp(-2 * length * (g - mu - lam) ** 2)


def tail_gap(excess: float, lam: float, length: int) -> float:
    """Classical bound by the spectral gap."""
    return math.exp(-length * (1 - lam) * excess**2 / 4)


def deviation(length: int) -> float:
    """Chance that a walk's sum of a function with tails exp(-x ln(x)^3) reaches C_DEV * length."""
    return math.exp(-length)


def deviation_constant() -> float:
    return math.e**2 + math.e**3 + math.e - 1


assert deviation_constant() <= C_DEV


def repetitions(delta_star: float, delta: float) -> int:
    return math.ceil(4 * math.log(1 / delta) / math.log(1 / delta_star))


def median_failure(l: int) -> float:  # noqa: E741
    return math.exp(-l / 4)


SPACE = {
    "bit_pattern": lambda n, e, d: n / e**2,
    "max_level": lambda n, e, d: math.log(n),
    "binned_max_level": lambda n, e, d: d * (math.log(n) / e**2 + math.log(1 / e) * math.log(n) * n),
    "rough_tracked": lambda n, e, d: d * (1 / e**2 + n),
    "walk_seeded": lambda n, e, d: d / e**2 + n,
    "single_cut_nested": lambda n, e, d: d / e**2 + n,
    "lower_bound": lambda n, e, d: d / e**2 + n,
}
MERGEABLE = {"bit_pattern": True, "max_level": True, "binned_max_level": True, "rough_tracked": False, "walk_seeded": False, "single_cut_nested": True, "lower_bound": None}


def space_formula(algorithm: str, bits: int, eps: float, delta: float) -> float:
    """Growth formula with all constants 1 (not bits): ln n, 1 / eps^2, ln(1 / delta)."""
    return SPACE[algorithm](bits * math.log(2), eps, math.log(1 / delta))


def walk_tail_mc(f: np.ndarray, neighbor, edge_count: int, length: int, g: float, walks: int, rng: np.random.Generator) -> float:
    """Share of random walks whose mean of f is at least g; ``neighbor`` maps arrays of (vertex, edge)."""
    v = rng.integers(0, len(f), walks)
    total = f[v].astype(float)
    for _ in range(length - 1):
        v = neighbor(v, rng.integers(0, edge_count, walks))
        total += f[v]
    return float((total >= g * length - 1e-9).mean())
