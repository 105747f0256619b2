"""A literal, slow sketch on Python integers, for comparison with the engine."""

import math


def bits(v):
    return int(math.floor(math.log2(v + 2)))


class Literal:
    def __init__(self, context):
        self.p, self.triples = context.params, context.triples
        self.cells = [[-1] * self.p.b for _ in range(self.p.l)]
        self.q = 0

    def put(self, x):
        other = Literal.__new__(Literal)
        other.p, other.triples, other.q = self.p, self.triples, 0
        other.cells = [[-1] * self.p.b for _ in range(self.p.l)]
        for row, t in zip(other.cells, self.triples, strict=True):
            row[t.bins(x)] = t.level(x)
        other.shrink()
        self.join(other)

    def join(self, other):
        q = max(self.q, other.q)
        self.cells = [[max(a + self.q - q, b + other.q - q, -1) for a, b in zip(x, y, strict=True)] for x, y in zip(self.cells, other.cells, strict=True)]
        self.q = q
        self.shrink()

    def shrink(self):
        while sum(bits(v) for row in self.cells for v in row) > self.p.space_limit:
            self.cells = [[max(v - 1, -1) for v in row] for row in self.cells]
            self.q += 1
