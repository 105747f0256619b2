"""Accuracy, event and cost measures of sketches and runs."""

from __future__ import annotations

import math

import numpy as np

from .cuts import cell_bits
from .functions.families import Triple
from .params import SketchParams
from .sketch import Sketch, rho, rho_inv


def relative_error(estimate: float, exact: int) -> float:
    return abs(estimate - exact) / exact if exact else float(estimate != 0)


def failure_rate(estimates, exact: int, eps: float) -> tuple[float, float, float]:
    """Share of estimates off by over eps, with a 95 % interval (Wilson)."""
    n, k = len(estimates), sum(relative_error(e, exact) > eps for e in estimates)
    p, z = k / n, 1.96
    mid, half = (p + z * z / (2 * n)) / (1 + z * z / n), z * math.sqrt(p * (1 - p) / n + z * z / (4 * n * n)) / (1 + z * z / n)
    return p, max(0.0, mid - half), min(1.0, mid + half)


def events(keys: np.ndarray, triple: Triple, p: SketchParams, eps: float) -> dict[str, bool | float]:
    """The four events of a table's analysis and what follows from them, for a set of distinct keys."""
    level = triple.level.many(keys)
    s = max(0, int(level.max()) - p.log_b + p.offset)
    sample = keys[level >= s]
    expected = len(keys) / 2**s
    pre = triple.bins.pre.many(sample) if triple.bins.pre else sample
    hits = len(np.unique(triple.bins.many(sample)))
    r = len(sample)
    return {
        "threshold": s,
        "load": expected,
        "load_ok": s == 0 or 2.0**-16 * p.b <= expected <= p.b / 2,
        "sample_ok": abs(r - expected) <= eps / 3 * expected,
        "no_collision": len(np.unique(pre)) == r,
        "hits_ok": abs(hits - float(rho(r, p.b))) <= 9 * r / math.sqrt(p.b),
        "sample": r,
        "hits": hits,
        "sample_small": r <= 2 * p.b / 3,
        "hits_small": hits <= 41 * p.b / 60,
        "slope_ok": float(rho_inv(min(hits + 1, p.b - 1), p.b) - rho_inv(hits, p.b)) < 4,
    }


def max_level_tail(k: int) -> float:
    """Bound of the chance that the largest of n levels is over ld n + k, or below ld n - k - 1, for any n."""
    return 2.0**-k


def cut_margin(sketch: Sketch, exact: int) -> dict[str, int | bool]:
    """The cut against the level that it stays below except with probability delta / 2."""
    q_max = max(0, math.ceil(math.log2(max(exact, 1))) - sketch.context.params.log_b)
    s = sketch.estimate().thresholds
    return {"q": sketch.q, "q_max": q_max, "q_ok": sketch.q <= q_max, "s_ok": bool((s >= q_max).all())}


def column_bits(levels: np.ndarray) -> np.ndarray:
    """Compressed cost of each table."""
    return cell_bits(levels).sum(axis=1)


def column_tail(c: int) -> float:
    """Bound of the chance that a table costs over (c + 3) bits per bin at the reference cut."""
    return 2.0 ** -(2.0**c)


def budget_ok(packed_bits: int, p: SketchParams) -> bool:
    """Whether the code's length keeps within (2 budget + 1) bits per cell and the cut's bits."""
    return packed_bits <= (2 * p.budget + 1) * p.b * p.l + p.d.bit_length()


def comm_bytes(seed_bits: int, sketch_bytes: int, processes: int) -> dict[str, int]:
    """What a distributed run moves: the seed to every process, one sketch from each; nothing in between."""
    return {"start": processes * ((seed_bits + 7) // 8), "end": processes * sketch_bytes, "merges": processes - 1}


def operation_counts(levels: np.ndarray, p: SketchParams) -> dict[str, int]:
    """Input size of a cut (the cost of all cells) and the operations of the one-shot form: cells, histogram, candidates."""
    return {"input": int(cell_bits(levels).sum()), "cells": levels.size, "candidates": (p.d + 2) ** 2}
