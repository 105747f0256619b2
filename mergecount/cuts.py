"""Where to cut: the least cut level at which a table of levels fits its space budget."""

from __future__ import annotations

import numpy as np


def cell_bits(levels) -> np.ndarray:
    """Cost of cells: floor(ld(level + 2)); an empty cell (-1) costs nothing."""
    return np.frexp(np.asarray(levels, dtype=np.int64) + 2)[1] - 1


def total_bits(levels: np.ndarray) -> int:
    return int(cell_bits(levels).sum())


def cost_matrix(top: int) -> np.ndarray:
    """Cost of a cell of level v (column v + 1) after a cut of c (row c), for all levels up to top."""
    levels = np.arange(-1, top + 1)
    return cell_bits(np.maximum(levels[None, :] - np.arange(top + 2)[:, None], -1))


def cut_curve(levels: np.ndarray) -> np.ndarray:
    """Total cost for every cut from 0 to top + 1, from one histogram of the levels."""
    top = max(0, int(levels.max(initial=-1)))
    return cost_matrix(top) @ np.bincount(levels.ravel().astype(np.int64) + 1, minlength=top + 2)


def required_cut(levels: np.ndarray, limit: int) -> int:
    """Least cut with cost at most ``limit``: linear in the table plus the square of the largest level."""
    return int(np.argmax(cut_curve(levels) <= limit))


def apply_cut(levels: np.ndarray, cut: int) -> np.ndarray:
    return np.maximum(levels.astype(np.int16) - cut, -1).astype(np.int8)


def compress_stepwise(levels: np.ndarray, q: int, limit: int) -> tuple[np.ndarray, int]:
    """The literal form, one level at a time; a reference for tests."""
    while total_bits(levels) > limit:
        levels, q = apply_cut(levels, 1), q + 1
    return levels, q


def cost_drops(level: int) -> list[int]:
    """Cuts at which a cell of this level gets one bit cheaper."""
    costs = [int(cell_bits(max(level - c, -1))) for c in range(level + 2)]
    return [c for c in range(1, level + 2) if costs[c] < costs[c - 1]]
