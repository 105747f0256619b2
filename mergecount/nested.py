"""The nested sketch for very small failure probabilities.

m copies of the single-cut sketch, each with its own cut, whose seeds are the vertices of an outer
walk: a vertex of the outer graph numbers a whole inner walk. The estimate is the median of the
copies' medians. Copies share nothing but the draw.
"""

from __future__ import annotations

import hashlib
import math
import struct
from dataclasses import dataclass, replace

import numpy as np

from . import cuts
from .functions.expander import WalkSpace
from .functions.seeding import Seed, draw, minus_log_delta, seed_bits
from .params import SketchParams, derive
from .sketch import Context, Sketch

_COUNT = struct.Struct(">I")


@dataclass(frozen=True)
class NestedParams:
    inner: SketchParams
    m: int
    delta: float
    inner_mode: str
    cuts: str = "copy"  # one cut per copy; 'shared' (one for all) and 'table' (one per table) are ablations


def copies_formula(delta: float, bits: int) -> int:
    return math.ceil(4 * math.log(1 / delta) / math.log(bits * math.log(2)))


def copies_inequality(delta: float, bits: int) -> int:
    """From the tail of the outer walk: m (ln(1 / (2 delta*)) / 2 - 2 / e) >= ln(1 / delta)."""
    gain = 0.5 * (minus_log_delta(bits) - math.log(2)) - 2 / math.e
    if gain <= 0:
        raise ValueError("universe too small for the nested sketch")
    return math.ceil(math.log(1 / delta) / gain)


def derive_nested(bits: int, eps: float, delta: float, profile: str = "practical", m: int | None = None, inner: SketchParams | None = None, cuts: str = "copy", **practical) -> NestedParams:
    """delta below 1 / ln n: copies of the sketch for delta* = 1 / ln n."""
    inner = inner or derive(bits, eps, 1 / (bits * math.log(2)), profile, **practical)
    m = m or max(copies_formula(delta, bits), copies_inequality(delta, bits))
    return NestedParams(inner, m, delta, "walk_paper" if inner.profile == "proof" else "walk_16", cuts)


def outer_space(p: NestedParams) -> WalkSpace:
    return WalkSpace(seed_bits(p.inner, p.inner_mode), minus_log_delta(p.inner.d), p.m)


def init_nested(p: NestedParams, entropy: int | str) -> list[Seed]:
    """Seeds of the copies from one draw."""
    space = outer_space(p)
    bits = seed_bits(p.inner, p.inner_mode)
    return [Seed(p.inner, p.inner_mode, v & ((1 << bits) - 1), bits) for v in space.unrank(draw(entropy, space.bits, "nested"))]


@dataclass(frozen=True)
class NestedSeed:
    """The draw of a run of the nested sketch: the seeds of all copies. Sketches of different draws never merge."""

    params: NestedParams
    seeds: tuple[Seed, ...]

    @property
    def fingerprint(self) -> int:
        text = f"{self.params.m},{self.params.delta},{self.params.cuts}|" + ",".join(str(s.fingerprint) for s in self.seeds)
        return int.from_bytes(hashlib.sha256(text.encode()).digest()[:8], "big", signed=True)

    @property
    def bits(self) -> int:
        return outer_space(self.params).bits


def nested_seed(params: NestedParams, entropy: int | str) -> NestedSeed:
    return NestedSeed(params, tuple(init_nested(params, entropy)))


def apply_shared_cut(parts: list[Sketch], limit: int) -> None:
    """One cut for all copies: the least at which all tables together fit one budget."""
    q = max(p.q for p in parts)
    whole = np.concatenate([cuts.apply_cut(p.levels, q - p.q) for p in parts])
    more = cuts.required_cut(whole, limit)
    for p in parts:
        p.levels, p.q = cuts.apply_cut(p.levels, q + more - p.q), q + more


class NestedSketch:
    """m copies of the single-cut sketch; the state is a function of the set of keys alone.

    With ``cuts = 'shared'`` the copies keep levels uncut and ``pack`` and ``estimate`` see them at one common cut.
    """

    def __init__(self, params: NestedParams, seeds: list[Seed] | tuple[Seed, ...], parts: list[Sketch] | None = None):
        self.params, self.seeds = params, seeds
        if params.cuts == "table":
            raise ValueError("a cut for each table has no packed form: see operators.nested_cells")
        self.parts = parts or [Sketch(self._context(s)) for s in seeds]

    def _context(self, seed: Seed) -> Context:
        return Context.of(replace(seed, params=replace(seed.params, budget=1e9)) if self.params.cuts == "shared" else seed)

    def update(self, keys: np.ndarray) -> NestedSketch:
        keys = np.unique(keys)
        for part in self.parts:
            part.update(keys)
        return self

    def merge(self, other: NestedSketch) -> NestedSketch:
        for mine, theirs in zip(self.parts, other.parts, strict=True):
            mine.merge(theirs)
        return self

    def _cut(self) -> list[Sketch]:
        parts = [Sketch(p.context, p.levels.copy(), p.q) for p in self.parts]
        if self.params.cuts == "shared":
            apply_shared_cut(parts, self.params.m * self.params.inner.space_limit)
        return parts

    def estimate(self) -> float:
        return float(np.median([p.estimate().value for p in self._cut()]))

    def pack(self, codec: str = "gamma") -> bytes:
        """All copies in one blob: their number, then each with its length."""
        blobs = [p.pack(codec) for p in self.parts]
        return _COUNT.pack(len(blobs)) + b"".join(_COUNT.pack(len(b)) + b for b in blobs)

    @classmethod
    def unpack(cls, seed: NestedSeed, data: bytes) -> NestedSketch:
        empty = cls(seed.params, seed.seeds)
        (m,), at, parts = _COUNT.unpack_from(data), _COUNT.size, []
        if m != seed.params.m:
            raise ValueError("sketches of different seeds or shapes do not merge")
        for part in empty.parts:
            (size,) = _COUNT.unpack_from(data, at)
            parts.append(Sketch.unpack(part.context, data[at + _COUNT.size : at + _COUNT.size + size]))
            at += _COUNT.size + size
        return cls(seed.params, seed.seeds, parts)

    def cut_bits(self) -> int:
        """Bits of all cut levels."""
        return cut_bits(self.params.cuts, self.params.m, self.params.inner.l, self.params.inner.d)


def cut_bits(kind: str, m: int, l: int, d: int = 64) -> int:  # noqa: E741
    """Bits of all cut levels: of one, of each copy, or of each table."""
    return max(1, math.ceil(math.log2(d + 1))) * {"shared": 1, "copy": m, "table": m * l}[kind]


def route(bits: int, delta: float, m_bits: int | None = None) -> str:
    """'single' for delta >= 1 / ln n, else 'nested'; 'exact' if the key columns have at most ``m_bits`` <= 10 bits: a bitmap is smaller than any sketch."""
    if m_bits is not None and m_bits <= 10:
        return "exact"
    return "single" if delta >= 1 / (bits * math.log(2)) else "nested"
