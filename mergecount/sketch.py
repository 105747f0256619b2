"""The single-cut sketch in memory: build, add, merge, compress, estimate."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

import numpy as np

from . import cuts, packed
from .functions.families import Triple
from .functions.seeding import Seed
from .params import SketchParams, independence

#: Keys that a sketch takes between two looks at its cut.
PIECE = 1 << 14


def rho(r, b: int):
    """Expected bins hit by r balls."""
    return -b * np.expm1(np.asarray(r, dtype=float) * math.log1p(-1 / b))


def rho_inv(hits, b: int):
    """Balls for which so many hits are expected; b - 1 hits at most."""
    return np.log1p(-np.minimum(np.asarray(hits, dtype=float), b - 1) / b) / math.log1p(-1 / b)


def rho_inv_table(b: int, tolerance: float) -> np.ndarray:
    """rho_inv for hits 0 to 41 b / 60, rounded to so many binary digits that every relative error is at most ``tolerance``."""
    hits = np.arange(0, 41 * b // 60 + 1)
    exact = rho_inv(hits, b)
    digits = math.ceil(math.log2(1 / tolerance)) - 1
    grid = np.exp2(np.floor(np.log2(np.maximum(exact, 1.0))) - digits)
    return np.where(hits == 0, 0.0, np.round(exact / grid) * grid)


@dataclass(frozen=True)
class Estimate:
    value: float
    q: int
    thresholds: np.ndarray
    hits: np.ndarray
    per_table: np.ndarray
    saturated: bool
    cut_ok: bool


class Context:
    """Seed and hash functions of a run, built once per process."""

    _open: dict[int, Context] = {}

    def __init__(self, seed: Seed):
        self.seed, self.params, self.fingerprint = seed, seed.params, seed.fingerprint
        self.triples: list[Triple] = seed.triples()

    @classmethod
    def of(cls, seed: Seed) -> Context:
        key = seed.fingerprint
        if key not in cls._open:
            cls._open[key] = cls(seed)
        return cls._open[key]


class Sketch:
    """State (levels, cut): a function of the set of keys alone, however they came."""

    def __init__(self, context: Context, levels: np.ndarray | None = None, q: int = 0):
        p = context.params
        self.context, self.q = context, q
        self.levels = np.full((p.l, p.b), -1, dtype=np.int8) if levels is None else levels

    # -- building -------------------------------------------------------------
    def update(self, keys: np.ndarray) -> Sketch:
        """Adds an array of uint64 keys. Keys below the cut in a table are not hashed to bins there: they could only make empty cells.

        The cut is raised after every ``PIECE`` keys, so that it spares the later ones; the state does not depend on it.
        """
        keys = np.unique(keys)
        for at in range(0, len(keys), PIECE):
            piece = keys[at : at + PIECE]
            for t, triple in enumerate(self.context.triples):
                level = triple.level.many(piece)
                kept = level >= self.q
                if kept.any():
                    bins = triple.bins.many(piece[kept])
                    np.maximum.at(self.levels[t], bins, (level[kept] - self.q).astype(np.int8))
            self.compress()
        return self.compress()

    def update_wide(self, keys: list[int]) -> Sketch:
        """Adds keys of any width as integers (universes beyond 64 bits, such as digests): one at a time. Levels over 127 above the cut count as 127."""
        for t, triple in enumerate(self.context.triples):
            for x in keys:
                level = triple.level(x)
                if level >= self.q:
                    j = triple.bins(x)
                    self.levels[t, j] = max(self.levels[t, j], min(127, level - self.q))
        return self.compress()

    def add(self, x: int) -> Sketch:
        return self.merge(single(self.context, x))

    def compress(self) -> Sketch:
        cut = cuts.required_cut(self.levels, self.context.params.space_limit)
        if cut:
            self.levels, self.q = cuts.apply_cut(self.levels, cut), self.q + cut
        return self

    def merge(self, other: Sketch) -> Sketch:
        if other.context.fingerprint != self.context.fingerprint:
            raise ValueError("sketches of different seeds or shapes do not merge")
        q = max(self.q, other.q)
        self.levels = np.maximum(cuts.apply_cut(self.levels, q - self.q), cuts.apply_cut(other.levels, q - other.q))
        self.q = q
        return self.compress()

    # -- results --------------------------------------------------------------
    def estimate(self, at_cut: int | None = None, inverse: np.ndarray | None = None) -> Estimate:
        """Median over the tables of the scaled inverse occupancy; ``at_cut`` forces a higher cut, ``inverse`` is a table (``rho_inv_table``) to look it up in.

        A rounded inverse costs accuracy, which four times the bins (``four_times_bins``) make up for.
        """
        levels, q = (self.levels, self.q) if at_cut is None else (cuts.apply_cut(self.levels, at_cut - self.q), at_cut)
        return estimate_levels(levels, q, self.context.params, inverse)

    def pack(self, codec: str = "gamma") -> bytes:
        return packed.encode(self.levels, self.q, self.context.fingerprint, codec)

    @classmethod
    def unpack(cls, context: Context, data: bytes) -> Sketch:
        levels, q, fingerprint = packed.decode(data)
        if fingerprint != context.fingerprint:
            raise ValueError("sketches of different seeds or shapes do not merge")
        return cls(context, levels.copy(), q)


def four_times_bins(p: SketchParams) -> SketchParams:
    """The same sketch with 4 b bins and the independence that they need, for estimates by a rounded inverse."""
    return replace(p, b=4 * p.b, k=independence(4 * p.b))


def estimate_levels(levels: np.ndarray, q: int, p: SketchParams, inverse: np.ndarray | None = None) -> Estimate:
    absolute = levels.astype(np.int64) + q
    s = np.maximum(0, absolute.max(axis=1) - p.log_b + p.offset)
    hits = ((absolute >= s[:, None]) & (levels >= 0)).sum(axis=1) if q else (absolute >= s[:, None]).sum(axis=1)
    balls = rho_inv(hits, p.b)
    if inverse is not None:  # hits beyond the table are exact
        balls = np.where(hits < len(inverse), inverse[np.minimum(hits, len(inverse) - 1)], balls)
    values = np.exp2(s) * balls
    return Estimate(float(np.median(values)), q, s, hits, values, bool((hits >= p.b).any()), bool((s >= q).all()))


def single(context: Context, x: int) -> Sketch:
    return Sketch(context).update(np.array([x], dtype=np.uint64))


def direct(context: Context, keys: np.ndarray) -> Sketch:
    """The state by definition: raw maximal levels of the set, then the least cut that fits."""
    out = Sketch(context)
    for t, triple in enumerate(context.triples):
        np.maximum.at(out.levels[t], triple.bins.many(keys), triple.level.many(keys))
    return out.compress()
