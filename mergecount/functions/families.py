"""Hash families with few random bits: k-wise polynomials, geometric levels, two-step bins."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from .field2 import Field, clmod


class PolyHash:
    """Polynomials of degree below k over GF(2^d), low ``c`` bits kept; k-wise independent.

    ``coefficients``: from the constant term up; k * d random bits.
    """

    def __init__(self, coefficients: list[int], d: int, c: int | None = None):
        self.coefficients, self.field, self.c = list(coefficients), Field(d), d if c is None else c
        self._words: np.ndarray | None = None

    @property
    def bits(self) -> int:
        return len(self.coefficients) * self.field.d

    def __call__(self, x: int) -> int:
        out = 0
        for a in reversed(self.coefficients):
            out = self.field.mul(out, x) ^ a
        return out & ((1 << self.c) - 1)

    def many(self, x: np.ndarray) -> np.ndarray:
        """Values at an array of points, d <= 64."""
        mask = np.uint64((1 << self.c) - 1)
        if len(self.coefficients) == 2:
            if self._words is None:
                self._words = self.nibbles()
            return lookup(self._words, x) & mask
        return np.concatenate([self._horner(x[i : i + 4096]) for i in range(0, max(len(x), 1), 4096)]) & mask

    def _horner(self, x: np.ndarray) -> np.ndarray:
        """Horner's rule; products by x take four bits of the other factor at a time from the multiples of x."""
        d, n = self.field.d, np.arange(len(x))
        if d > 60:
            out = np.zeros(len(x), dtype=np.uint64)
            for a in reversed(self.coefficients):
                out = self.field.mul_np(x, out) ^ np.uint64(a)
            return out
        multiples = np.zeros((16, len(x)), dtype=np.uint64)
        multiples[1] = x
        for j in range(2, 16):
            multiples[j] = multiples[j - 1] ^ x if j & 1 else self._doubled(multiples[j // 2])
        folded = np.array([clmod(i << d, self.field.modulus) for i in range(16)], dtype=np.uint64)
        low, four, fifteen, top = np.uint64((1 << d) - 1), np.uint64(4), np.uint64(15), np.uint64(d)
        shifts = [np.uint64(s) for s in range((d - 1) // 4 * 4, -1, -4)]
        out = np.full(len(x), self.coefficients[-1], dtype=np.uint64)
        for a in reversed(self.coefficients[:-1]):
            product = multiples[((out >> shifts[0]) & fifteen).astype(np.intp), n]
            for s in shifts[1:]:
                product <<= four
                product = (product & low) ^ folded[(product >> top).astype(np.intp)] ^ multiples[((out >> s) & fifteen).astype(np.intp), n]
            out = product ^ np.uint64(a)
        return out

    def _doubled(self, x: np.ndarray) -> np.ndarray:
        d = self.field.d
        y = x << np.uint64(1)
        return np.where(y >> np.uint64(d), y ^ np.uint64(self.field.modulus), y)

    def nibbles(self) -> np.ndarray:
        """For two coefficients the map is affine over GF(2): 16 x 16 words whose XOR, one for each four bits of x, is the value."""
        constant, slope = self.coefficients
        table = np.zeros((16, 16), dtype=np.uint64)
        for place in range(16):
            for v in range(16):
                x = v << (4 * place)
                part = self.field.mul(slope, x) if x < 1 << self.field.d else 0
                table[place, v] = part ^ (constant if place == 0 else 0)
        return table


def lookup(table: np.ndarray, x: np.ndarray) -> np.ndarray:
    """XOR of a word for each four bits of x; places at which all of x are zero have one word in common."""
    used = -(-int(np.bitwise_or.reduce(x)).bit_length() // 4) if len(x) else 0
    out = np.full(len(x), np.bitwise_xor.reduce(table[used:, 0]), dtype=np.uint64)
    for place in range(used):
        out ^= table[place][((x >> np.uint64(4 * place)) & np.uint64(15)).astype(np.intp)]
    return out


def trailing_zeros(words: np.ndarray, d: int) -> np.ndarray:
    """Trailing zeros of d-bit words; d for zero."""
    low = words & (~words + np.uint64(1))
    out = np.bitwise_count(low - np.uint64(1)).astype(np.int8)
    return np.where(words == 0, np.int8(d), out)


class LevelHash:
    """Pairwise independent levels: at least j with probability 2^-j, at most d."""

    def __init__(self, coefficients: list[int], d: int):
        self.poly, self.d = PolyHash(coefficients, d), d

    def __call__(self, x: int) -> int:
        y = self.poly(x)
        return self.d if y == 0 else (y & -y).bit_length() - 1

    def many(self, x: np.ndarray) -> np.ndarray:
        return trailing_zeros(self.poly.many(x), self.d)


class BinHash:
    """Bins in two steps: pairwise to 32 b^2 values, then k-wise to b; with one step if ``pre`` is None."""

    def __init__(self, pre: PolyHash | None, bins: PolyHash):
        self.pre, self.bins = pre, bins

    def __call__(self, x: int) -> int:
        return self.bins(x if self.pre is None else self.pre(x))

    def many(self, x: np.ndarray) -> np.ndarray:
        return self.bins.many(x if self.pre is None else self.pre.many(x)).astype(np.int32)


@dataclass(frozen=True)
class Triple:
    """Hash functions of one table."""

    level: LevelHash
    bins: BinHash

    def many(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return self.level.many(x), self.bins.many(x)
