"""SimHash prints, their anchors, and the pipeline's candidates, which come from them."""

import numpy as np
import pytest

import corpus_pipeline as cp
from mergecount.llm import anchors, jaccard
from tests.llm.test_jaccard import brute_components, edited


def literal_nearest(value, words):
    return int(words[np.argmin(np.bitwise_count(words ^ value))])


def test_the_code_is_perfect():
    """4,096 words at least 7 bits apart; every value is within 3 bits of the one that is found."""
    words = np.unique(anchors.nearest(np.arange(1 << 23)))
    assert len(words) == 4096 == len(np.unique(words >> 11))
    assert min(int(w).bit_count() for w in words if w) == 7  # the code is linear, so this is its distance
    assert {int(a ^ b) for a in words[:64] for b in words[:64]} <= set(words.tolist())
    values = np.random.default_rng(1).integers(0, 1 << 23, 500)
    assert anchors.nearest(values).tolist() == [literal_nearest(v, words) for v in values]
    assert (np.bitwise_count(anchors.nearest(np.arange(1 << 23)) ^ np.arange(1 << 23)) <= 3).all()


@pytest.mark.parametrize("size", [0, 1, 2, 4, 5, 254, 255, 256, 700])
def test_print_is_the_majority_of_its_members(size):
    own = np.unique(np.random.default_rng(size).integers(0, 1 << 63, size, dtype=np.uint64))
    counts = np.zeros(64 * anchors.WORDS, dtype=int)
    for one in own:
        counts += np.unpackbits(anchors.print_of(np.array([one])).view(np.uint8))
    got = np.unpackbits(anchors.print_of(own).view(np.uint8)).astype(bool)
    assert not got[counts * 2 < len(own)].any() and got[counts * 2 > len(own)].all()
    tied = counts * 2 == len(own)
    if size in (2, 4):
        assert 0.4 < got[tied].mean() < 0.6


def pair(rng, one, other, both):
    every = rng.integers(0, 1 << 63, one + other - both, dtype=np.uint64)
    return np.sort(every[:one]), np.sort(np.concatenate([every[:both], every[one:]]))


@pytest.mark.parametrize("one,other,both", [(4, 5, 4), (5, 6, 5), (6, 7, 6), (9, 9, 8), (8, 10, 8), (12, 15, 12), (20, 25, 20), (90, 90, 80), (240, 300, 240)])
def test_pairs_at_the_cut_meet(one, other, both):
    """At a similarity of 0.8, whatever the sizes, an anchor is shared and the sketches are near."""
    rng = np.random.default_rng(one)
    met = 0
    for _ in range(200):
        a, b = (anchors.prints_of(x) for x in pair(rng, one, other, both))
        x, y = (anchors.anchors_of(p) for p in (a, b))
        shared = [(i, j) for i in range(len(a)) for j in range(len(b)) if (x[i] == y[j]).any()]
        met += any(np.bitwise_count(a[i] ^ b[j])[: anchors.SKETCH].sum() <= anchors.NEAR for i, j in shared)
    assert met >= 199


@pytest.mark.parametrize("n", [0, 1, 2, 200, 700])
def test_groups_equal_brute_force(n):
    rng = np.random.default_rng(n)
    base = rng.integers(0, 1 << 63, (max(1, n // 10), anchors.SKETCH), dtype=np.uint64)
    rows = base[rng.integers(0, len(base), n)].copy()
    for row in rows:
        for at in rng.integers(0, 192, rng.integers(0, 50)):
            row[at // 64] ^= np.uint64(1) << np.uint64(at % 64)
    near = np.bitwise_count(rows[:, None] ^ rows).sum(axis=2) <= anchors.NEAR
    expected, seen = set(), set()
    for i in range(n):
        group, front = {i}, [i]
        while front:
            new = set(np.flatnonzero(near[front.pop()]).tolist()) - group
            group |= new
            front += new
        if len(group) > 1 and i not in seen:
            expected.add(frozenset(group))
        seen |= group
    assert {frozenset(g.tolist()) for g in anchors.groups([rows[:, k] for k in range(anchors.SKETCH)])} == expected


@pytest.fixture(scope="module")
def texts():
    rng = np.random.default_rng(11)
    docs = [None, "", "a b c d e f g h", "a b c d e f g h i", "one two", "x " * 40]
    for changes in (1, 4, 8):
        for _ in range(12):
            words = [f"w{x}" for x in rng.integers(0, 5000, 220)]
            docs += [" ".join(words), edited(rng, words, changes)]
    base = [f"v{x}" for x in rng.integers(0, 5000, 150)]
    docs += [edited(rng, base, 1) for _ in range(60)]
    return list(enumerate(docs))


@pytest.mark.parametrize("cell", [6, 1 << 15])
def test_stage_takes_its_candidates_from_anchors(spark, texts, monkeypatch, cell):
    """The stage keeps one of each group of a comparison of all pairs, and asks the anchors for all of its candidates, crowded anchors too."""
    asked, crowds = [], anchors.crowds
    monkeypatch.setattr(anchors, "CELL", cell)
    monkeypatch.setattr(anchors, "crowds", lambda prints: asked.append(prints.count()) or crowds(prints))
    df = spark.createDataFrame([(i, t, "en", "s", 1) for i, t in texts], "doc_id long, text string, lang string, source string, n_chars long")
    kept = sorted(r["doc_id"] for r in cp.near_duplicate_stage(spark, df, "").collect())
    assert kept == sorted(set(brute_components(texts).values()))
    assert asked == [len({jaccard.shingle_set((t or "").encode(), 5).tobytes() for _, t in texts})]
