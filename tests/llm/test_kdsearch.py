"""The search against all pairs, on vectors that boxes can and can't tell apart."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from mergecount.llm import kdsearch


def table(spark, v):
    return kdsearch.whole_vectors(spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(v)], "vec_id long, embedding array<double>"), "vec_id", "embedding").cache()


def all_pairs(v, step, k=10):
    x = np.floor(1024 * v).astype(np.int64)
    out = []
    for q in range(0, len(x), step):
        s = x @ x[q]
        order = [i for i in np.lexsort((np.arange(len(x)), -s)) if i != q][:k]
        out += [(q, r + 1, int(i), int(s[i])) for r, i in enumerate(order)]
    return sorted(out)


def clustered(rng, rows, dims):
    """Many tight groups far apart, a third of all rows equal."""
    centres = rng.normal(size=(40, dims)) * 5
    v = centres[rng.integers(0, 40, rows)] + rng.normal(size=(rows, dims)) * 0.05
    v[rng.random(rows) < 1 / 3] = centres[0]
    return v


@pytest.mark.parametrize("kind", ["clustered", "random"])
def test_equals_all_pairs(spark, monkeypatch, kind):
    monkeypatch.setattr(kdsearch, "SHARD_ROWS", 200)
    monkeypatch.setattr(kdsearch, "BLOCK", 30)
    monkeypatch.setattr(kdsearch, "GROUP", 3)
    rng = np.random.default_rng(7)
    v = clustered(rng, 3000, 6) if kind == "clustered" else rng.normal(size=(1500, 16)) / 4
    vectors = table(spark, v)
    got = kdsearch.top_k(vectors, vectors.filter("id % 20 = 0"), leaf=16).collect()
    assert sorted(map(tuple, got)) == all_pairs(v, 20)


def test_boxes_prune_where_they_can(spark, monkeypatch):
    monkeypatch.setattr(kdsearch, "SHARD_ROWS", 500)
    rng = np.random.default_rng(8)
    vectors = table(spark, clustered(rng, 6000, 6))
    near = kdsearch.visited(vectors, vectors.filter("id % 20 = 0"), leaf=16)
    loose = table(spark, rng.normal(size=(3000, 64)) / 8)
    far = kdsearch.visited(loose, loose.filter("id % 20 = 0"), leaf=16)
    assert near < 0.25, near
    assert far > 0.9, far  # 64 independent dimensions: boxes admit too much, as the module says


def test_overflow_raises(spark):
    big = table(spark, np.full((3, 2), 2.0**40))
    with pytest.raises(Exception, match="63 bits"):
        kdsearch.top_k(big, big.filter(F.col("id") == 0)).collect()
