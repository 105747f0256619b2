"""The score must not depend on whether the sample of labelled rows is capped."""

import numpy as np

from mergecount.llm import toxicity


def logit(p):
    return float(np.log(p) - np.log1p(-p))


def test_capped_sample_keeps_the_prior(spark):
    rng = np.random.default_rng(2)
    rows, labels = [], []
    for i in range(2400):
        toxic = i % 12 == 0
        words = [f"{a}lm" for a in rng.choice(list("bcdfghjk"), 40)]
        if rng.random() < (0.5 if toxic else 0.08):
            words[5] = "vile"
        rows.append((i, " ".join(words)))
        labels.append((i, int(toxic)))
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(2).cache()
    labels = spark.createDataFrame(labels, "doc_id long, toxic int")
    probe = "vile " + " ".join(["blm", "clm", "dlm", "flm"] * 10)
    found = []
    for sample in (4000, 120):  # no cap reached; clean rows capped to about as many as toxic ones
        model = toxicity.fit(docs, labels, sample)
        wanted = {k: i for i, k in enumerate(model.keys)}
        assert wanted
        z = (toxicity.features(probe, wanted, toxicity.first_letters(model.keys)) - model.mean) / model.scale
        found.append(float(z @ model.weights + model.bias))
    assert abs(found[0] - found[1]) < 1.0, found  # ln 11 = 2.4 if the capped classes' ratio is taken as the prior
