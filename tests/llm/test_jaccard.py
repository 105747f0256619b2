"""The pipeline's near-duplicates: links of 5-word shingle sets at Jaccard 0.8 or more."""

import numpy as np
import pyarrow as pa
import pytest

from mergecount.llm import jaccard, simhash


def literal_set(text):
    words = (text or "").lower().split()
    return {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()


def brute_components(docs, similarity=0.8):
    sets = [literal_set(t) for _, t in docs]
    root = {i: i for i, _ in docs}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for k, (a, _) in enumerate(docs):
        for m in range(k + 1, len(docs)):
            x, y = sets[k], sets[m]
            if (len(x & y) >= similarity * len(x | y)) and bool(x) == bool(y):
                p, q = sorted((find(a), find(docs[m][0])))
                root[q] = p
    return {i: find(i) for i, _ in docs}


def edited(rng, words, changes):
    out = list(words)
    for at in rng.choice(len(out), changes, replace=False):
        out[at] = f"x{rng.integers(1 << 40)}"
    return " ".join(out)


@pytest.fixture(scope="module")
def texts():
    rng = np.random.default_rng(3)
    docs = [None, "", "One two", "one TWO"]
    for changes in (1, 2, 3, 4, 5, 6, 8, 12):  # Jaccard about 0.95 down to 0.5
        for _ in range(8):
            words = [f"w{x}" for x in rng.integers(0, 5000, 200)]
            docs += [" ".join(words), edited(rng, words, changes)]
    base = [f"v{x}" for x in rng.integers(0, 5000, 100)]
    docs += [edited(rng, base, 1) for _ in range(90)]  # one large group
    docs += [edited(rng, base, 3) for _ in range(90)]  # hardly alike, in shared keys: compared in cells
    return list(enumerate(docs))


def test_near_duplicates_equal_brute_force(spark, texts):
    df = spark.createDataFrame(texts, "doc_id long, text string")
    got = {r["doc_id"]: r["component_id"] for r in simhash.near_duplicates(df).collect()}
    assert got == brute_components(texts)


def test_stage_keeps_one_of_each_group(spark, texts):
    import corpus_pipeline as cp

    df = spark.createDataFrame([(i, t, "en", "s", 1) for i, t in texts], "doc_id long, text string, lang string, source string, n_chars long")
    kept = sorted(r["doc_id"] for r in cp.near_duplicate_stage(spark, df, "").collect())
    assert kept == sorted(set(brute_components(texts).values()))


def test_recall_of_the_bands():
    """Pairs at 0.8 or a little more nearly always share a key."""
    rng = np.random.default_rng(4)
    met = total = 0
    while total < 300:
        words = [f"w{x}" for x in rng.integers(0, 9999, 300)]
        a, b = (jaccard.shingle_set(t.encode(), 5) for t in (" ".join(words), edited(rng, words, 7)))
        if 0.8 <= jaccard.similarity_of(a, b) < 0.86:
            total += 1
            met += bool(set(jaccard.band_keys(a)) & set(jaccard.band_keys(b)))
    assert met >= 299


def test_intersections_by_products(monkeypatch):
    rng = np.random.default_rng(6)
    monkeypatch.setattr(jaccard, "_COLUMNS", 7)
    sets = [np.unique(rng.integers(0, 60, n).astype(np.uint64)) for n in (0, 1, 5, 30, 30, 55)] + [np.zeros(0, dtype=np.uint64)]
    expected = [[len(np.intersect1d(a, b)) if i != j or len(a) else 0 for j, b in enumerate(sets)] for i, a in enumerate(sets)]
    got = jaccard.overlaps(sets)
    for i in range(len(sets)):
        for j in range(len(sets)):
            assert i == j or got[i, j] == expected[i][j]


@pytest.mark.parametrize("cell", [3, 512])
def test_cells_of_any_size_give_the_same_components(spark, monkeypatch, cell):
    """A crowd of half similar texts with one key: cut in many cells or in one."""
    monkeypatch.setattr(jaccard, "CELL", cell)
    rng = np.random.default_rng(9)
    base = [f"w{i}" for i in range(60)]
    texts = []
    for i in range(60):
        words = list(base)
        for at in rng.choice(60, rng.integers(1, 4), replace=False):
            words[at] = f"x{rng.integers(0, 6)}"
        texts.append((i, " ".join(words)))
    got = jaccard.near_duplicates(spark.createDataFrame(texts, "doc_id long, text string"), "doc_id", "text", 5, 0.8).collect()
    root = list(range(60))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    sets = [jaccard.shingle_set(t.encode(), 5) for _, t in texts]
    for i in range(60):
        for j in range(i):
            if jaccard.similarity_of(sets[i], sets[j]) >= 0.8:
                a, b = sorted((find(i), find(j)))
                root[b] = a
    assert {r["doc_id"]: r["component_id"] for r in got} == {i: find(i) for i in range(60)}


def family(rng, n, words=60, most=4):
    base = [f"w{i}" for i in range(words)]
    return [edited(rng, base, int(rng.integers(1, most + 1))) for _ in range(n)]


def test_a_class_is_dealt_once_however_many_keys_it_has(spark, monkeypatch):
    """30 keys of the same classes, not all connected: the comparison of all pairs gets a row for each class, not one for each key."""

    def counted(*_):
        def run(batches):
            for batch in batches:
                yield pa.RecordBatch.from_arrays([pa.array([batch.num_rows]), pa.array([-1])], names=["a", "b"])

        return run

    texts = [t.encode() for t in family(np.random.default_rng(5), 40)]
    crowd = spark.createDataFrame([(k, fp) for k in range(30) for fp in range(40)], "key long, fp long")
    monkeypatch.setattr(jaccard, "_compare_cells", counted)
    found = jaccard.links(crowd, spark.createDataFrame(list(enumerate(texts)), "fp long, text binary"), 5, 0.8)
    assert sum(r["a"] for r in found.filter("b = -1").collect()) == 40


@pytest.mark.parametrize("cell,size", [(7, 1 << 23), (1 << 8, 900), (1 << 8, 1 << 23)])
def test_cells_hold_all_pairs_that_can_be_linked(spark, monkeypatch, cell, size):
    """Of each group all pairs of two roots whose sizes allow a similarity of 0.8 meet, on two sides or in one chunk; large parts are not dealt to themselves."""
    monkeypatch.setattr(jaccard, "CELL", cell)
    monkeypatch.setattr(jaccard, "CELL_BYTES", size)
    rng = np.random.default_rng(cell)
    rows = []
    for fp in range(150):
        group, n = int(rng.choice([1, 1, 1, 2, 3])), int(rng.choice([0, 1, 4, 5, 20, 25, 64, 80, 100]))
        root = group * 1000 + int(rng.choice([0, 0, 1, 10 + fp]))
        rows.append((fp, root, group, n, np.arange(n, dtype=np.uint64).tobytes()))
    df = spark.createDataFrame(rows, "fp long, root long, group long, size long, set binary")
    dealt = {}
    for r in jaccard.cells(df, 0.8).collect():
        dealt.setdefault((r["group"], r["i"], r["j"]), []).append((r["fp"], r["side"]))
    met = set()
    for (_, i, j), own in dealt.items():
        assert len(own) == len(set(own))
        met |= {(x, y) for x, a in own for y, b in own if x < y and (i == j or a != b)}
    pairs = [(a, b) for a in rows for b in rows if a[0] < b[0] and a[2] == b[2]]
    assert {(a[0], b[0]) for a, b in pairs if a[1] != b[1] and min(a[3], b[3]) >= 0.8 * max(a[3], b[3])} <= met <= {(a[0], b[0]) for a, b in pairs}
    if cell == 7:
        of = {r[0]: r for r in rows}
        many = {(r[1], r[2]) for r in rows if sum(x[1:3] == r[1:3] for x in rows) > cell}
        assert many and not any(of[x][1:3] == of[y][1:3] and of[x][1:3] in many for x, y in met)
        assert len(met) < len(pairs) / 2


@pytest.mark.parametrize("cell", [8, 40])
def test_wide_groups_equal_brute_force(spark, monkeypatch, cell):
    """Families with parts larger than a cell, texts of other sizes that contain a family's text, and a pair at exactly 0.8."""
    monkeypatch.setattr(jaccard, "CELL", cell)
    rng = np.random.default_rng(12)
    texts = family(rng, 90) + family(rng, 40, 70)
    base = [f"w{i}" for i in range(60)]
    texts += [" ".join(base[:n]) for n in (30, 36, 48, 49)] + [" ".join(base + [f"y{i}" for i in range(n)]) for n in (5, 14, 30)]
    docs = list(enumerate(texts))
    crowd = spark.createDataFrame([(k, fp) for k in range(3) for fp, _ in docs if fp % 4 != k], "key long, fp long")
    found = jaccard.links(crowd, spark.createDataFrame([(i, t.encode()) for i, t in docs], "fp long, text binary"), 5, 0.8).collect()
    root = list(range(len(docs)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for r in found:
        a, b = sorted((find(r["a"]), find(r["b"])))
        root[b] = a
    assert {i: find(i) for i, _ in docs} == brute_components(docs)
