"""Strongly explicit expander graphs and their walks.

The base graph has the points of the torus Z_M x Z_M and the degree 8: four affine shears and their
inverses. Its second eigenvalue is at most 5 sqrt(2) / 8 of the degree, for every M. Powers of it
(t steps make one hop) reach any smaller bound. This is another construction than the zig-zag
product that theory often names; only the bound and the explicit neighbours matter here.
"""

from __future__ import annotations

import numpy as np

from ..params import hop_steps

DEGREE = 8


class Graph:
    """2^bits vertices; ``-ln`` of the spectral bound gives the steps of a hop. Parallel edges count."""

    def __init__(self, bits: int, minus_log_lambda: float):
        self.bits = bits + bits % 2  # an odd number of bits gets one that nothing reads
        self.side = 1 << (self.bits // 2)
        self.steps = hop_steps(minus_log_lambda)

    @property
    def edge_bits(self) -> int:
        return 3 * self.steps

    def step(self, v: int, e: int) -> int:
        m = self.side - 1
        x, y = v & m, v >> (self.bits // 2)
        sign, shear = (1 if e < 4 else -1), e % 4
        extra = shear & 1
        if shear < 2:
            y = (y + sign * (2 * x + extra)) & m
        else:
            x = (x + sign * (2 * y + extra)) & m
        return x | y << (self.bits // 2)

    def neighbor(self, v: int, edge: int) -> int:
        for _ in range(self.steps):
            v, edge = self.step(v, edge & 7), edge >> 3
        return v

    def matrix(self) -> np.ndarray:
        """Transition matrix of the base graph, for small sizes."""
        n = 1 << self.bits
        out = np.zeros((n, n))
        for v in range(n):
            for e in range(DEGREE):
                out[v, self.step(v, e)] += 1 / DEGREE
        return out


def torus_matrix(m: int) -> np.ndarray:
    """Transition matrix of the base graph on Z_m x Z_m for any m."""
    out = np.zeros((m * m, m * m))
    for x in range(m):
        for y in range(m):
            for sign in (1, -1):
                for extra in (0, 1):
                    out[x * m + y, x * m + (y + sign * (2 * x + extra)) % m] += 1 / DEGREE
                    out[x * m + y, (x + sign * (2 * y + extra)) % m * m + y] += 1 / DEGREE
    return out


class WalkSpace:
    """All walks of ``length`` vertices, numbered: the start vertex, then the edge of every hop."""

    def __init__(self, vertex_bits: int, minus_log_lambda: float, length: int):
        self.graph, self.length, self.vertex_bits = Graph(vertex_bits, minus_log_lambda), length, vertex_bits

    @property
    def bits(self) -> int:
        return self.graph.bits + (self.length - 1) * self.graph.edge_bits

    def split(self, number: int) -> tuple[int, list[int]]:
        g = self.graph
        start, rest = number & ((1 << g.bits) - 1), number >> g.bits
        mask = (1 << g.edge_bits) - 1
        return start, [rest >> (i * g.edge_bits) & mask for i in range(self.length - 1)]

    def rank(self, start: int, edges: list[int]) -> int:
        g = self.graph
        return start | sum(e << (g.bits + i * g.edge_bits) for i, e in enumerate(edges))

    def unrank(self, number: int) -> list[int]:
        """Vertices of a walk (without the padding bit)."""
        v, edges = self.split(number)
        walk = [v]
        for e in edges:
            walk.append(v := self.graph.neighbor(v, e))
        return [w & ((1 << self.vertex_bits) - 1) for w in walk]
