import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from mergecount import bounds, cuts, measures, nested, packed
from mergecount.baselines.rough_tracked import RoughTracked
from mergecount.functions import seeding
from mergecount.params import SketchParams, independence
from mergecount.sketch import Context, Sketch, direct, estimate_levels, rho, rho_inv, rho_inv_table, single
from tests.ref_sketch import Literal

SMALL = SketchParams(3, 16, 4, budget=1.0)
CTX = Context.of(seeding.init(SMALL, "tests"))
KEYS = st.lists(st.integers(0, 2**64 - 1), max_size=60)


def of(keys):
    return Sketch(CTX).update(np.array(keys, dtype=np.uint64))


@settings(max_examples=40, deadline=None)
@given(KEYS, KEYS, KEYS)
def test_merge_laws(a, b, c):
    x = of(a).merge(of(b)).merge(of(c)).pack()
    assert x == of(c).merge(of(a).merge(of(b))).pack() == of(a + b + c + a).pack() == direct(CTX, np.unique(np.array(a + b + c, dtype=np.uint64))).pack()
    assert of(a).merge(of(a)).pack() == of(a).pack() == of(a).merge(Sketch(CTX)).pack()


@settings(max_examples=15, deadline=None)
@given(KEYS)
def test_literal_form(keys):
    slow = Literal(CTX)
    for k in keys:
        slow.put(k)
    fast = of(keys)
    assert fast.q == slow.q and fast.levels.tolist() == slow.cells


def test_cut_is_monotone_and_moves():
    s, last = Sketch(CTX), 0
    for n in range(0, 4000, 200):
        s.update(np.arange(n, n + 200, dtype=np.uint64))
        assert s.q >= last
        last = s.q
    assert last > 0


@settings(max_examples=50, deadline=None)
@given(st.lists(st.integers(-1, 64), min_size=1, max_size=80), st.integers(0, 200))
def test_cut_forms_agree(values, limit):
    levels = np.array([values], dtype=np.int8)
    cut = cuts.required_cut(levels, limit)
    slow, q = cuts.compress_stepwise(levels, 0, limit)
    assert q == cut and (cuts.apply_cut(levels, cut) == slow).all()
    assert cut == 0 or cuts.total_bits(cuts.apply_cut(levels, cut - 1)) > limit


def test_worked_example():
    assert cuts.cost_drops(23) == [10, 18, 22, 24]


def test_proof_budget_never_cuts():
    assert cuts.required_cut(np.full((2, 8), 64, dtype=np.int8), 33 * 16) == 0


def test_estimates():
    p = SketchParams(9, 1024, independence(1024))
    c = Context.of(seeding.init(p, 3))
    assert Sketch(c).estimate().value == 0
    assert round(single(c, 7).estimate().value) == 1
    for n in (10, 500, 5000):
        e = Sketch(c).update(np.arange(n, dtype=np.uint64) * np.uint64(7919)).estimate()
        assert measures.relative_error(e.value, n) < 0.15 and e.cut_ok and not e.saturated


def test_forced_cut_below_threshold_keeps_estimate():
    p = SketchParams(3, 64, 6, budget=50.0)
    s = Sketch(Context.of(seeding.init(p, 5))).update(np.arange(3000, dtype=np.uint64))
    base = s.estimate()
    low = int(base.thresholds.min())
    assert low > 0
    for q in range(low + 1):
        assert s.estimate(q).value == base.value
    assert not s.estimate(int(base.thresholds.max()) + 1).cut_ok


def test_saturation_is_flagged():
    e = estimate_levels(np.zeros((1, 8), dtype=np.int8), 0, SketchParams(1, 8, 2, offset=2))
    assert e.saturated and math.isfinite(e.value)


def test_seeds_do_not_mix():
    with pytest.raises(ValueError):
        of([1]).merge(Sketch(Context.of(seeding.init(SMALL, "other"))))


@pytest.mark.parametrize("codec", packed.CODECS)
def test_packing(codec):
    s = of(list(range(300)))
    data = s.pack(codec)
    back = Sketch.unpack(CTX, data)
    assert (back.levels == s.levels).all() and back.q == s.q
    if codec == "gamma":
        body = len(data) - packed._HEAD.size
        cell_bits = packed.size_bits(s.levels, s.q) - max(1, s.q.bit_length())
        assert body == -(-cell_bits // 8) and measures.budget_ok(cell_bits, SMALL)


def test_occupancy_inverse():
    r = np.arange(0, 200)
    assert np.allclose(rho_inv(rho(r, 256), 256), r)
    table = rho_inv_table(256, 0.01)
    exact = rho_inv(np.arange(len(table)), 256)
    assert (np.abs(table - exact) <= 0.01 * exact + 1e-9).all()


def test_balls_in_bins_with_default_independence():
    """Hits stay within 9 r / sqrt(b) of the expected number in nearly all draws."""
    b, bad = 256, 0
    for draw in range(60):
        t = seeding.TripleSpace(SketchParams(1, b, independence(b))).decode(seeding.draw(draw, 4096, "balls"))
        r = 200
        hits = len(np.unique(t.bins.many(np.arange(r, dtype=np.uint64))))
        bad += abs(hits - float(rho(r, b))) > 9 * r / math.sqrt(b)
    assert bad <= 2


def test_nested():
    assert nested.copies_formula(1e-6, 64) == 15 and nested.copies_inequality(1e-6, 64) == 17
    assert nested.copies_inequality(1e-6, 256) == 10 and nested.route(64, 0.1) == "single" and nested.route(64, 1e-6) == "nested"
    p = nested.derive_nested(64, 0.3, 1e-6, inner=SketchParams(3, 64, 6), m=3)
    seeds = nested.init_nested(p, 1)
    keys = np.arange(900, dtype=np.uint64)
    whole = nested.NestedSketch(p, seeds).update(keys)
    parts = nested.NestedSketch(p, seeds).update(keys[:500]).merge(nested.NestedSketch(p, seeds).update(keys[300:]))
    assert [a.pack() for a in whole.parts] == [a.pack() for a in parts.parts]
    assert measures.relative_error(whole.estimate(), 900) < 0.4
    sizes = [nested.cut_bits(c, 3, 3) for c in ("shared", "copy", "table")]
    assert sizes[0] < sizes[1] < sizes[2]
    shared = nested.NestedSketch(nested.NestedParams(p.inner, 3, 1e-6, "walk_16", "shared"), seeds).update(keys)
    cut = shared._cut()
    total = sum(cuts.total_bits(a.levels) for a in cut)
    raw = np.concatenate([a.levels for a in shared.parts])
    assert len({a.q for a in cut}) == 1 and total <= 3 * p.inner.space_limit  # one budget over all copies,
    assert cut[0].q == 0 or cuts.total_bits(cuts.apply_cut(raw, cut[0].q - 1)) > 3 * p.inner.space_limit  # and no cut above the least
    seed = nested.nested_seed(p, 1)
    assert nested.NestedSketch.unpack(seed, whole.pack()).pack() == parts.pack()
    assert nested.route(64, 1e-6, 8) == "exact"


def test_rough_tracked_depends_on_order_and_never_merges():
    c = Context.of(seeding.init(SketchParams(3, 64, 6, budget=1.2), "rough", "independent"))
    rng = np.random.default_rng(0)
    flags = {tuple(RoughTracked(c).add(rng.permutation(3000).astype(np.uint64)).failed) for _ in range(6)}
    assert any(any(f) for f in flags)
    with pytest.raises(TypeError):
        RoughTracked(c).merge(RoughTracked(c))
    ok = RoughTracked(Context.of(seeding.init(SketchParams(5, 256, 8, budget=4.0), "rough", "walk_16"))).add(np.arange(2000, dtype=np.uint64))
    assert measures.relative_error(ok.estimate(), 2000) < 0.4 and ok.rough_bits(True) < ok.rough_bits(False)


def test_bounds():
    assert bounds.deviation_constant() <= 30
    for mu, lam, g in ((0.1, 0.01, 0.5), (0.02, 0.0, 0.3)):
        assert bounds.kl(g, mu + lam) >= bounds.kl_lower(g, mu + lam)
        assert bounds.tail_kl(mu, lam, g, 10) <= bounds.tail_log(mu, lam, g, 10)
        assert bounds.tail_kl(mu, lam, g, 10) <= bounds.tail_quadratic(mu, lam, g, 10)
        exact, simple = bounds.hitting(mu, lam, 3)
        assert exact <= simple
    with pytest.raises(ValueError):
        bounds.tail_kl(0.5, 0.1, 0.55, 5)
    with pytest.raises(ValueError):
        bounds.tail_kl_2010(0.1, 0.1, 0.3, 5)
    assert bounds.repetitions(1 / math.log(2**64), 1e-6) == 15


def test_events():
    t = CTX.triples[0]
    e = measures.events(np.arange(10, dtype=np.uint64), t, SMALL, 0.5)
    assert e["threshold"] == 0 or e["sample"] <= 10
    assert e["hits"] <= e["sample"]
    assert measures.failure_rate([1.0, 2.0], 1, 0.1)[0] == 0.5


def test_wide_universe():
    p = SketchParams(5, 64, 6, d=256)
    keys = [seeding.draw(i, 256, "wide") for i in range(150)]
    c = Context.of(seeding.init(p, "wide", "independent"))
    a = Sketch(c).update_wide(keys)
    b = Sketch(c).update_wide(keys[80:]).merge(Sketch(c).update_wide(keys[:100]))
    assert a.pack() == b.pack() and measures.relative_error(a.estimate().value, 150) < 0.5


def test_one_stage_bins_estimate_alike():
    p = SketchParams(7, 256, 8)
    c = Context(seeding.init(p, "one"))
    c.triples = seeding.one_stage_triples(p, "one")
    e = Sketch(c).update(np.arange(700, dtype=np.uint64)).estimate()
    assert measures.relative_error(e.value, 700) < 0.3
    assert measures.comm_bytes(100, 50, 4) == {"start": 52, "end": 200, "merges": 3}
    assert measures.operation_counts(np.zeros((2, 4), dtype=np.int8), p)["input"] == 8
