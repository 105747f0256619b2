"""Arithmetic of GF(2^d): carry-less products modulo an irreducible polynomial."""

from __future__ import annotations

from functools import lru_cache

import numpy as np


def clmul(a: int, b: int) -> int:
    out = 0
    while b:
        low = b & -b
        out ^= a * low
        b ^= low
    return out


def clmod(a: int, m: int) -> int:
    width = m.bit_length()
    while a.bit_length() >= width:
        a ^= m << (a.bit_length() - width)
    return a


def _gcd(a: int, b: int) -> int:
    while b:
        a, b = b, clmod(a, b)
    return a


def is_irreducible(m: int) -> bool:
    """Rabin's test."""
    d = m.bit_length() - 1
    if d < 1:
        return False
    primes = [p for p in range(2, d + 1) if d % p == 0 and all(p % q for q in range(2, p))]
    power, powers = 2, {0: 2}  # x^(2^i) mod m
    for i in range(1, d + 1):
        power = clmod(clmul(power, power), m)
        powers[i] = power
    if powers[d] != clmod(2, m):
        return False
    return all(_gcd(m, powers[d // p] ^ 2) == 1 for p in primes)


@lru_cache(maxsize=None)
def find_irreducible(d: int) -> int:
    """The least irreducible polynomial of degree d, as a bit mask."""
    return next(m for m in range((1 << d) + (d > 0), 1 << (d + 1), 2 if d > 1 else 1) if is_irreducible(m))


class Field:
    def __init__(self, d: int):
        self.d, self.modulus = d, find_irreducible(d)

    def mul(self, a: int, b: int) -> int:
        return clmod(clmul(a, b), self.modulus)

    def power(self, a: int, n: int) -> int:
        out = 1
        while n:
            if n & 1:
                out = self.mul(out, a)
            a, n = self.mul(a, a), n >> 1
        return out

    def inverse(self, a: int) -> int:
        if not a:
            raise ZeroDivisionError
        return self.power(a, (1 << self.d) - 2)

    def mul_np(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Products of arrays of field elements, d <= 64: shift and add, most significant bit of b first."""
        top, low = np.uint64(1 << (self.d - 1)), np.uint64(self.modulus & ((1 << self.d) - 1))
        mask = np.uint64((1 << self.d) - 1)
        out = np.zeros(np.broadcast(a, b).shape, dtype=np.uint64)
        for i in range(self.d - 1, -1, -1):
            over = (out & top) != 0
            out = (out << np.uint64(1)) & mask
            out ^= np.where(over, low, np.uint64(0))
            out ^= np.where((b >> np.uint64(i)) & np.uint64(1), a, np.uint64(0))
        return out
