import itertools
import math
from collections import Counter

import numpy as np
import pytest

from mergecount.functions import expander, seeding
from mergecount.functions.families import BinHash, LevelHash, PolyHash, trailing_zeros
from mergecount.functions.field2 import Field, find_irreducible, is_irreducible
from mergecount.params import SketchParams, derive, independence, inner_lambda_log


@pytest.mark.parametrize("d", [1, 2, 3, 4])
def test_field_axioms(d):
    f, n = Field(d), range(1 << d)
    for a, b, c in itertools.product(n, n, n):
        assert f.mul(a, f.mul(b, c)) == f.mul(f.mul(a, b), c)
        assert f.mul(a, b ^ c) == f.mul(a, b) ^ f.mul(a, c)
    for a in list(n)[1:]:
        assert f.mul(a, f.inverse(a)) == 1


def test_irreducible():
    small = [m for m in range(16, 32) if is_irreducible(m)]
    assert small == [0b10011, 0b11001, 0b11111]
    assert find_irreducible(8) == 0b100011011


def test_numpy_products_equal_integers():
    rng = np.random.default_rng(0)
    for d in (5, 25, 64):
        f = Field(d)
        a, b = (rng.integers(0, 1 << 63, 50).astype(np.uint64) & np.uint64((1 << d) - 1) for _ in range(2))
        assert f.mul_np(a, b).tolist() == [f.mul(int(x), int(y)) for x, y in zip(a, b, strict=True)]


@pytest.mark.parametrize("k,d", [(2, 3), (3, 2)])
def test_kwise_uniform(k, d):
    """Over all seeds any k points take all value tuples equally often."""
    points = list(range(1 << d))[:k]
    seen = Counter(tuple(PolyHash(list(c), d)(x) for x in points) for c in itertools.product(range(1 << d), repeat=k))
    assert set(seen.values()) == {1} and len(seen) == 1 << (d * k)


def test_level_law():
    d = 4
    levels = Counter(LevelHash([a, b], d)(5) for a in range(16) for b in range(16))
    for j in range(d + 1):
        assert sum(n for v, n in levels.items() if v >= j) == 256 >> j


@pytest.mark.parametrize("d,k", [(25, 9), (13, 4), (64, 2), (8, 5)])
def test_many_equals_one(d, k):
    rng = np.random.default_rng(1)
    h = PolyHash([int(v) for v in rng.integers(0, 1 << min(d, 62), k)], d, min(d, 7))
    x = rng.integers(0, 1 << min(d, 62), 99).astype(np.uint64)
    assert h.many(x).tolist() == [h(int(v)) for v in x]


def test_trailing_zeros():
    words = np.array([0, 1, 8, 1 << 63, (1 << 64) - 1, 6], dtype=np.uint64)
    assert trailing_zeros(words, 64).tolist() == [64, 0, 3, 63, 0, 1]


@pytest.mark.parametrize("m", [4, 8, 12])
def test_torus_gap(m):
    t = expander.torus_matrix(m)
    assert np.allclose(t, t.T) and np.allclose(t.sum(axis=1), 1)
    second = np.sort(np.abs(np.linalg.eigvalsh(t)))[-2]
    assert second <= 5 * math.sqrt(2) / 8


def test_graph_steps_are_the_torus():
    g = expander.Graph(4, 0.1)
    m = g.matrix()
    assert np.allclose(m, m.T) and np.allclose(m.sum(axis=0), 1)
    assert np.sort(np.abs(np.linalg.eigvalsh(m)))[-2] <= 5 * math.sqrt(2) / 8


def test_walk_numbering_is_a_bijection():
    space = expander.WalkSpace(2, 0.1, 3)
    walks = Counter()
    for n in range(1 << space.bits):
        assert space.rank(*space.split(n)) == n
        walks[space.unrank(n)[-1]] += 1
    assert set(walks.values()) == {(1 << space.bits) // 4}  # every vertex equally often at every step


def test_params():
    p = derive(64, 0.5, 0.1)
    assert (p.l, p.log_b, p.offset, p.budget) == (12, 29, 9, 33.0)
    assert derive(64, 0.1, 0.05).log_b == 33 and derive(64, 0.01, 0.01).log_b == 40
    assert inner_lambda_log(12) > 180 and inner_lambda_log(12, "walk_16") == math.log(16)
    with pytest.raises(ValueError):
        SketchParams(5, 256, 8, offset=9)


def test_seed_bits():
    p = SketchParams(12, 2**12, independence(2**12))
    assert seeding.TripleSpace(p).bits == 2547
    assert seeding.seed_bits(p, "walk_16") < seeding.seed_bits(p, "independent") < seeding.seed_bits(p, "walk_paper")
    a, b = seeding.init(p, 1), seeding.init(p, 2)
    assert a.fingerprint == seeding.init(p, 1).fingerprint != b.fingerprint


def test_two_step_bins_in_range():
    p = SketchParams(3, 64, 6)
    for t in seeding.init(p, "x").triples():
        assert isinstance(t.bins, BinHash)
        assert all(0 <= t.bins(x) < 64 for x in (0, 1, 2**63, 2**64 - 1))
