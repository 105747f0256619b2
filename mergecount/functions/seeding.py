"""Seeds: the hash functions of all tables from one random draw."""

from __future__ import annotations

import hashlib
import math
from dataclasses import dataclass

from ..params import SketchParams, inner_lambda_log
from .expander import WalkSpace
from .families import BinHash, LevelHash, PolyHash, Triple

MODES = ("walk_16", "walk_paper", "independent")


def draw(entropy: int | str, bits: int, label: str = "") -> int:
    """``bits`` bits from an extendable-output hash of the entropy: the same on every machine."""
    raw = hashlib.shake_256(f"{label}|{entropy}".encode()).digest((bits + 7) // 8)
    return int.from_bytes(raw, "big") & ((1 << bits) - 1)


class TripleSpace:
    """Numbers of ``bits`` bits as hash functions of one table."""

    def __init__(self, params: SketchParams):
        self.p = params
        self.pre_field = max(params.d, params.pre_bits)
        self.bits = 2 * params.d + 2 * self.pre_field + params.k * params.pre_bits

    def decode(self, number: int) -> Triple:
        p = self.p
        at = 0

        def take(width: int) -> int:
            nonlocal at
            at += width
            return number >> (at - width) & ((1 << width) - 1)

        level = LevelHash([take(p.d), take(p.d)], p.d)
        pre = PolyHash([take(self.pre_field), take(self.pre_field)], self.pre_field, p.pre_bits)
        return Triple(level, BinHash(pre, PolyHash([take(p.pre_bits) for _ in range(p.k)], p.pre_bits, p.log_b)))


@dataclass(frozen=True)
class Seed:
    """Common to a whole run; sketches of different seeds never merge. ``blob`` rebuilds it anywhere."""

    params: SketchParams
    mode: str
    number: int
    bits: int

    @property
    def blob(self) -> bytes:
        return self.number.to_bytes((self.bits + 7) // 8, "big")

    @property
    def fingerprint(self) -> int:
        p = self.params
        text = f"{p.l},{p.b},{p.k},{p.d},{p.offset},{p.budget},{self.mode}|".encode() + self.blob
        return int.from_bytes(hashlib.sha256(text).digest()[:8], "big", signed=True)

    def triples(self) -> list[Triple]:
        space = TripleSpace(self.params)
        if self.mode == "independent":
            mask = (1 << space.bits) - 1
            numbers = [self.number >> (i * space.bits) & mask for i in range(self.params.l)]
        else:
            numbers = walk_space(self.params, self.mode).unrank(self.number)
        return [space.decode(x) for x in numbers]


def walk_space(params: SketchParams, mode: str) -> WalkSpace:
    return WalkSpace(TripleSpace(params).bits, inner_lambda_log(params.l, mode), params.l)


def seed_bits(params: SketchParams, mode: str) -> int:
    return params.l * TripleSpace(params).bits if mode == "independent" else walk_space(params, mode).bits


def init(params: SketchParams, entropy: int | str, mode: str | None = None) -> Seed:
    """The one random draw of a run."""
    mode = mode or ("walk_paper" if params.profile == "proof" else "walk_16")
    if mode not in MODES:
        raise ValueError(f"mode is one of {MODES}")
    bits = seed_bits(params, mode)
    return Seed(params, mode, draw(entropy, bits, "seed"), bits)


def minus_log_delta(bits: int) -> float:
    """-ln of the inner failure probability 1 / ln(2^bits)."""
    return math.log(bits * math.log(2))


def one_stage_triples(params: SketchParams, entropy: int | str) -> list[Triple]:
    """Variant without the pairwise first step: k-wise bins straight from the keys, k * d seed bits for each table."""
    out = []
    for t in range(params.l):
        words = [draw(entropy, params.d, f"one-stage-{t}-{i}") for i in range(params.k + 2)]
        out.append(Triple(LevelHash(words[:2], params.d), BinHash(None, PolyHash(words[2:], params.d, params.log_b))))
    return out
