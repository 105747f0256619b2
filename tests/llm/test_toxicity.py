"""The label model, the classifier's features and the bounds of the samples, against plain versions."""

import math
import re
import tracemalloc
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from mergecount.llm import toxicity


def drawn(rows, rng):
    """Votes of a known model: voters 0 to 5 depend on the class alone, voter 6 repeats voter 0 nine times in ten, voter 7 is noise."""
    y = rng.random(rows) < 0.2
    rate = np.where(y[:, None], [0.7, 0.6, 0.8, 0.5, 0.6, 0.7], [0.05, 0.1, 0.02, 0.1, 0.05, 0.1])
    v = (rng.random((rows, 6)) < rate).astype(float)
    copy = np.where(rng.random(rows) < 0.9, v[:, 0], rng.random(rows) < 0.5)
    return y, np.column_stack([v, copy, rng.random(rows) < 0.3]).astype(float)


def test_label_model_recovers_accuracies_and_dependencies():
    rng = np.random.default_rng(3)
    y, v = drawn(20_000, rng)
    guess = np.array([[0.1] * 6 + [0.1, 0.3], [0.5] * 6 + [0.5, 0.3]])  # rough, the same for all voters
    model, post = toxicity.fit_label_model(v, 0.2, guess)
    assert abs(post.mean() - y.mean()) < 0.02 and ((post > 0.5) == y).mean() > 0.96
    pairs = {frozenset((i, int(p))) for i, p in enumerate(model.parent) if p >= 0}
    assert frozenset((0, 6)) in pairs and not any(7 in p for p in pairs)
    for voter, (clean, toxic) in {1: (0.1, 0.6), 2: (0.02, 0.8), 3: (0.1, 0.5)}.items():
        found = [float((v[:, voter] * w).sum() / w.sum()) for w in (1 - post, post)]
        assert abs(found[0] - clean) < 0.03 and abs(found[1] - toxic) < 0.05
    # the repeated voter must not count twice: a model without dependencies is surer of rows where both vote
    loose = toxicity.LabelModel(0.2, np.full(8, -1), np.stack([np.stack([(v * w[:, None]).sum(axis=0) / w.sum()] * 2) for w in (1 - post, post)]))
    both = np.zeros((1, 8))
    both[0, [0, 6]] = 1
    assert model.posterior(both)[0] < loose.posterior(both)[0] - 0.1


def test_posterior_equals_the_written_out_product():
    rng = np.random.default_rng(4)
    parent, rates = np.array([-1, 0, 1, -1]), rng.uniform(0.1, 0.9, (2, 2, 4))
    v = np.array([[(k >> j) & 1 for j in range(4)] for k in range(16)], dtype=float)
    got = toxicity.LabelModel(0.3, parent, rates).posterior(v)
    for row, value in zip(v, got, strict=True):
        chance = []
        for y in (0, 1):
            p = 0.3 if y else 0.7
            for j in range(4):
                g = int(row[parent[j]]) if parent[j] >= 0 else 0
                p *= rates[y, g, j] if row[j] else 1 - rates[y, g, j]
            chance.append(p)
        assert abs(value - chance[1] / sum(chance)) < 1e-9


def literal_score(text, model):
    """The classifier by hand, from words and counts."""
    text = text or ""
    words = re.findall(r"[^\W\d_]+", text)
    n, low = max(1, len(words)), [w.lower() for w in words]
    hit = lambda w, k: w == k[:-1] if k.endswith(" ") else w.startswith(k) and len(w) >= len(k)
    x = [math.log1p(1000 * sum(hit(w, k) for w in low) / n) for k in model.keys]
    hits = sum(any(hit(w, k) for k in model.keys) for w in low)
    caps = sum(len(w) > 1 and w.isupper() for w in words)
    x += [math.log1p(1000 * hits / n), math.log1p(hits), caps / n, text.count("!") / max(1, len(text)), len(re.findall(r"[!%&#*$]{2,}", text)) / n]
    z = sum((a - m) / s * w for a, m, s, w in zip(x, model.mean, model.scale, model.weights, strict=True)) + model.bias
    return 1 / (1 + math.exp(-max(-30, min(30, z))))


def test_scores_equal_the_literal_scorer(spark):
    sf = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    model = toxicity.fit(docs, spark.read.parquet(f"{sf}/labels.parquet"))
    assert model.keys
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    for r in toxicity.score(docs, model).collect():
        assert abs(r["toxicity_score"] - literal_score(texts[r["doc_id"]], model)) < 1e-9


@pytest.fixture
def hot(spark):
    """Half of all rows have one id; every text of it is another one."""
    docs = spark.range(4000).select(F.when(F.col("id") % 2 == 0, 8).otherwise(F.col("id")).alias("doc_id"), F.concat(F.lit("text "), F.col("id").cast("string")).alias("text")).cache()
    return docs, docs.select("doc_id", (F.col("doc_id") % 5 == 0).cast("int").alias("toxic"))


def test_samples_are_bounded_and_apart(spark, hot):
    docs, labels = hot
    few, every = toxicity.labelled_sample(docs, labels, 50)
    ids = [r["doc_id"] for r in few.collect()]
    assert len(ids) == len(set(ids)) <= 100 and all(zlib.crc32(str(i).encode()) % 3 != 1 for i in ids)
    assert sum(every.values()) == labels.filter(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 != 1).count()
    known = {r["text"] for r in few.collect()}
    free = [r["text"] for r in toxicity.unlabelled_sample(docs, few, 200).collect()]
    assert 20 < len(free) <= 200 and not known & set(free)


def test_labels_of_the_label_models_rows_do_not_matter(spark):
    """Labels beyond the sample change the prior alone: turned into null they leave the lexicon as it is."""
    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    held = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1
    turned = labels.withColumn("toxic", F.when(held, 1 - F.col("toxic")).otherwise(F.col("toxic")))
    a, b = toxicity.fit(docs, labels), toxicity.fit(docs, turned)
    assert a.keys == b.keys and np.allclose(a.weights, b.weights) and a.bias == b.bias


def sparse(x):
    row, place = np.nonzero(x)
    return toxicity.Rows(np.searchsorted(row, np.arange(len(x) + 1)), place.astype(np.uint16), x[row, place], x.shape[1])


def test_fits_hold_a_block_of_rows_and_equal_the_fit_of_all(monkeypatch):
    """The driver's share of the limits: 6,000 rows of 261 features are 12.5 MB as numbers, of which the fits held many copies."""
    rng = np.random.default_rng(6)
    x = rng.random((6000, 261)) * (rng.random((6000, 261)) < 0.03)
    x[5] = 0
    rows, y = sparse(x), rng.random(6000)
    assert np.array_equal(np.concatenate(list(rows.blocks())), x)
    tracemalloc.start()
    model, post = toxicity.fit_label_model(rows.votes(256), 0.1, np.stack([np.full(262, 0.02), np.full(262, 0.1)]), rounds=6)
    fitted = toxicity.fit_linear(rows, post)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 16e6, peak  # over 80e6 with all rows at once
    monkeypatch.setattr(toxicity, "BLOCK", 10_000)
    whole, every = toxicity.fit_label_model(rows.votes(256), 0.1, np.stack([np.full(262, 0.02), np.full(262, 0.1)]), rounds=6)
    assert np.array_equal(model.parent, whole.parent) and np.allclose(post, every, atol=1e-9)
    for a, b in zip(fitted, toxicity.fit_linear(rows, post), strict=True):
        assert np.allclose(a, b, atol=1e-9)
    w, bias, mean, scale = toxicity.fit_linear(rows, y)
    assert np.allclose(mean, x.mean(axis=0)) and np.allclose(scale, np.maximum(x.std(axis=0), 1e-3))
    z = (x - mean) / scale
    assert np.abs(z.T @ (y - 1 / (1 + np.exp(-(z @ w + bias)))) - 3.0 * w).max() < 1e-5  # no slope is left
