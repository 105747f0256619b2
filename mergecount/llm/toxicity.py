"""Toxicity by weak supervision.

1. Voters. From a bounded sample of labelled rows (``SAMPLE`` of each class at most, picked by hash; never
   rows with crc32(doc_id) mod 3 = 1) every word and word beginning of 3 to 8 letters is counted by
   class. Entries tied to toxic rows (likelihood ratio over ``LEAST_RATIO`` for the rows that no entry
   chosen before accounts for) are the lexicon, ``KEYS`` at most. A lexicon voter votes where its share of
   the words is at least ``RATE``; pattern voters look at the whole lexicon's share and hits, capitals,
   exclamation and symbols, and at the lexicon's absence. That is all that labels do, but for the share of
   toxic rows among all usable labels and a prior of each voter's rates worth ``STRENGTH`` rows.
2. Label model. A generative model of the votes given the unseen class: P(y) times the product of
   P(vote | y, vote of the voter that it hangs on). Which voter hangs on which is a maximum spanning forest of
   the votes' mutual information within the classes (edges that are not significant are left out),
   estimated anew as the classes clear; accuracies and dependencies are the tables of that forest, fitted by
   expectation maximization. It sees ``MODEL_ROWS`` documents at most, picked by hash from all documents
   but the sample of 1 and the held-out remainder, and none of their labels.
3. Classifier. Logistic regression on lexicon and pattern features of those documents, fitted to the
   posteriors.
4. Every whole text is scored, where it lies: no shuffle. The model (some hundred numbers) is broadcast.

Labels, language, source and id are never inputs of a score.

Edge cases: null, empty and blank texts get the classifier's score of a text without words; with no
labelled rows (or one class only) the lexicon is empty and every score is the share of toxic rows, or
0 if there are none; where all documents are labelled the label model sees the sample's texts; repeated
rows score alike, and an id that is repeated gives one text (the least) to the fit; an empty table gives
an empty result; extra columns are ignored by the query and kept by ``score``.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common as C

#: Labelled rows of each class at most, documents of the label model at most, lexicon entries, share of words at which an entry votes.
SAMPLE, MODEL_ROWS, KEYS, RATE, CUT = 4000, 12_000, 256, 0.002, 0.7
#: Rows that the fits hold as numbers at once.
BLOCK = 512
#: Log-likelihood gain that an entry needs, rows that the prior of a voter's rates is worth, G statistic of an edge (two degrees, 0.001).
LEAST_RATIO, STRENGTH, EDGE = 8.0, 10.0, 13.8
PATTERNS = 6
LENGTHS = range(3, 9)
_WORDS = re.compile(r"[^\W\d_]+")
_SYMBOLS = re.compile(r"[!%&#*$]{2,}")


class Model(NamedTuple):
    keys: tuple[str, ...]
    weights: np.ndarray
    bias: float
    mean: np.ndarray
    scale: np.ndarray


def word_counts(text: str | None) -> tuple[Counter, int, int]:
    """Counts of the lower-case words of a text, their number, and how many are in capitals."""
    counts: Counter = Counter()
    caps = 0
    for word, n in Counter(_WORDS.findall(text or "")).items():
        caps += n if len(word) > 1 and word.isupper() else 0
        counts[word.lower()] += n
    return counts, sum(counts.values()), caps


def entries(word: str) -> list[str]:
    """Lexicon entries that a word can match: itself (closed by a blank) and its beginnings."""
    return [word + " ", *(word[:k] for k in LENGTHS if len(word) >= k)]


def entry_counts(counts: Counter, wanted: dict[str, int] | None = None, first: set[str] | None = None) -> Counter:
    out: Counter = Counter()
    for word, n in counts.items():
        if first is None or word[:3] in first:
            for e in entries(word):
                if wanted is None or e in wanted:
                    out[e] += n
    return out


def features(text: str | None, wanted: dict[str, int], first: set[str]) -> np.ndarray:
    """Shares (log of 1 + share per thousand) of the entries, then patterns: lexicon share and hits, capitals, marks, symbols."""
    text = text or ""
    words = _WORDS.findall(text)
    n, caps = len(words), sum(len(w) > 1 for w in words if w.isupper())
    x, hits = np.zeros(len(wanted) + 5), 0
    for word, k in Counter(w for w in map(str.lower, words) if w[:3] in first).items():  # few words begin like an entry
        own = [wanted[e] for e in entries(word) if e in wanted]
        x[own] += k
        hits += k if own else 0
    size, chars = max(n, 1), max(len(text), 1)
    x[: len(wanted)] = np.log1p(1000 * x[: len(wanted)] / size)
    x[-5:] = np.log1p(1000 * hits / size), np.log1p(hits), caps / size, text.count("!") / chars, len(_SYMBOLS.findall(text)) / size
    return x


def first_letters(keys) -> set[str]:
    return {k.rstrip(" ")[:3] for k in keys}


def _mine(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(entry, toxic, n): rows of a class in which the entry has at least RATE of the words."""
    totals: tuple[Counter, Counter] = (Counter(), Counter())
    for batch in batches:
        for text, toxic in zip(batch.column(0), batch.column(1).to_pylist(), strict=True):
            counts, n, _ = word_counts(text.as_py())
            totals[toxic].update(e for e, k in entry_counts(counts).items() if k >= RATE * n)
    for toxic, counter in enumerate(totals):
        yield pa.RecordBatch.from_arrays([pa.array(counter.keys(), pa.string()), pa.array([toxic] * len(counter), pa.int32()), pa.array(counter.values(), pa.int64())], names=["entry", "toxic", "n"])


def gain(a: np.ndarray, b: np.ndarray, toxic: int, clean: int) -> np.ndarray:
    """Log-likelihood that a and b rows of the classes gain by two rates over one; 0 if the toxic rate isn't over 4 times the other."""
    p, q, r = (a + 0.5) / (toxic + 1), (b + 0.5) / (clean + 1), (a + b + 0.5) / (toxic + clean + 1)
    bits = lambda k, n, x: k * np.log(x) + (n - k) * np.log1p(-np.minimum(x, 1 - 1e-9))
    return np.where(p > 4 * q, bits(a, toxic, p) + bits(b, clean, q) - bits(a, toxic, r) - bits(b, clean, r), 0.0)


def pick_keys(stats: pd.DataFrame, toxic: int, clean: int) -> list[str]:
    """Entries most tied to toxic rows. One that a chosen entry begins adds nothing; one that begins chosen entries must be worth it without their rows."""
    a, b, entry = stats["n1"].to_numpy(float), stats["n0"].to_numpy(float), stats["entry"].to_numpy()
    ratio = gain(a, b, toxic, clean)
    order = np.lexsort((entry, -stats["entry"].str.len().to_numpy(), -ratio))
    chosen: list[tuple[str, float, float]] = []
    for i in order[ratio[order] > LEAST_RATIO]:
        if any(entry[i].startswith(e.rstrip()) for e, _, _ in chosen):
            continue
        inside = [(x, z) for e, x, z in chosen if e.startswith(entry[i].rstrip())]
        left = np.array([a[i] - sum(x for x, _ in inside)]), np.maximum(0, np.array([b[i] - sum(z for _, z in inside)]))
        if left[0][0] >= 3 and gain(*left, toxic, clean)[0] > LEAST_RATIO:
            chosen.append((entry[i], a[i], b[i]))
            if len(chosen) == KEYS:
                break
    return [e for e, _, _ in chosen]


def votes(x: np.ndarray, keys: int) -> np.ndarray:
    """Votes (1 or 0) of all voters: lexicon entries, patterns, and the lexicon's absence."""
    share, hits, caps, marks, symbols = x[:, keys:].T
    patterns = [share > np.log1p(10), hits > np.log(3), caps > 0.5, marks > 0.02, symbols > 0.2, hits == 0]
    return np.column_stack([x[:, :keys] >= np.log1p(1000 * RATE), *patterns]).astype(np.float64)


class LabelModel(NamedTuple):
    prior: float
    parent: np.ndarray  # the voter that each one hangs on, -1 for none
    rates: np.ndarray  # [class, parent's vote, voter]: chance of a vote

    def posterior(self, v: np.ndarray) -> np.ndarray:
        """Chance of the toxic class for each row of votes."""
        above = (np.where(self.parent >= 0, v[:, np.maximum(self.parent, 0)], 0) == 1) & (self.parent >= 0)
        odds = np.full(len(v), np.log(self.prior) - np.log1p(-self.prior))
        for y, sign in ((1, 1), (0, -1)):
            p = np.where(above, self.rates[y, 1], self.rates[y, 0])
            odds += sign * np.where(v == 1, np.log(p), np.log1p(-p)).sum(axis=1)
        return 1 / (1 + np.exp(-np.clip(odds, -30, 30)))


class Rows(NamedTuple):
    """Features that are not zero, row by row (few of a text's are): their places and values."""

    ends: np.ndarray  # where each row begins, and the end of the last
    place: np.ndarray
    value: np.ndarray
    width: int

    def __len__(self) -> int:
        return len(self.ends) - 1

    def blocks(self) -> Iterator[np.ndarray]:
        """The rows, all features, ``BLOCK`` rows at a time."""
        for at in range(0, len(self), BLOCK):
            ends = self.ends[at : at + BLOCK + 1]
            x = np.zeros((len(ends) - 1, self.width))
            x[np.repeat(np.arange(len(x)), np.diff(ends)), self.place[ends[0] : ends[-1]]] = self.value[ends[0] : ends[-1]]
            yield x

    def votes(self, keys: int) -> np.ndarray:
        return np.concatenate([np.zeros((0, keys + PATTERNS), dtype=np.uint8), *[votes(x, keys).astype(np.uint8) for x in self.blocks()]])


def _parts(rows: int) -> list[slice]:
    return [slice(at, at + BLOCK) for at in range(0, rows, BLOCK)]


def forest(v: np.ndarray, post: np.ndarray) -> np.ndarray:
    """The voter that each voter hangs on: a maximum spanning forest of mutual information within the classes."""
    n, voters = v.shape
    info = np.zeros((voters, voters))
    for w in (post, 1 - post):
        size = w.sum() + 1
        one, both = (sum(w[k] @ v[k] for k in _parts(n)) + 0.5) / size, (sum((v[k] * w[k, None]).T @ v[k] for k in _parts(n)) + 0.25) / size
        cells = ((both, one, one), (one[:, None] - both, one, 1 - one), (one[None, :] - both, 1 - one, one), (1 - one[:, None] - one[None, :] + both, 1 - one, 1 - one))
        for joint, p, q in cells:
            joint = np.maximum(joint, 1e-12)
            info += size / (n + 2) * joint * np.log(joint / np.maximum(np.outer(p, q), 1e-12))
    parent, best, source, done = np.full(voters, -1), np.zeros(voters), np.full(voters, -1), np.zeros(voters, dtype=bool)
    for _ in range(voters):
        k = int(np.argmax(np.where(done, -1.0, best)))
        parent[k] = source[k] if best[k] > EDGE / (2 * n) else -1
        done[k] = True
        closer = ~done & (info[k] > best)
        best[closer], source[closer] = info[k][closer], k
    return parent


def fit_label_model(v: np.ndarray, prior: float, expected: np.ndarray, rounds: int = 60) -> tuple[LabelModel, np.ndarray]:
    """The label model of votes without labels, and its posteriors. ``expected`` [class, voter]: the rates that the prior assumes."""
    alone = np.full(v.shape[1], -1)
    model = LabelModel(prior, alone, np.stack([expected, expected], axis=1))
    parts = _parts(len(v))
    posterior = lambda m: np.concatenate([np.zeros(0), *[m.posterior(v[k]) for k in parts]])
    post = posterior(model)
    for k in range(rounds):
        parent = forest(v, post) if k % 5 == 0 else model.parent
        cast, seen = np.zeros((2, 2, v.shape[1])), np.zeros((2, 2, v.shape[1]))
        for part in parts:
            own = v[part]
            above = (np.where(parent >= 0, own[:, np.maximum(parent, 0)], 0) == 1) & (parent >= 0)
            for y, w in ((0, 1 - post[part]), (1, post[part])):
                for g in (0, 1):
                    on = (above == g) * w[:, None]
                    cast[y, g] += (on * own).sum(axis=0)
                    seen[y, g] += on.sum(axis=0)
        model = LabelModel(prior, parent, (cast + STRENGTH * expected[:, None]) / (seen + STRENGTH))
        moved, post = post, posterior(model)
        if k % 5 == 4 and np.abs(moved - post).max() < 1e-4:
            break
    return model, post


def fit_linear(x: Rows, y: np.ndarray, ridge: float = 3.0, steps: int = 30) -> tuple[np.ndarray, float, np.ndarray, np.ndarray]:
    """Logistic regression on soft labels by Newton steps."""
    mean = sum(part.sum(axis=0) for part in x.blocks()) / len(x)
    scale = np.maximum(np.sqrt(sum(((part - mean) ** 2).sum(axis=0) for part in x.blocks()) / len(x)), 1e-3)
    w, penalty = np.zeros(x.width + 1), np.full(x.width + 1, ridge)
    penalty[-1] = 1e-6
    for _ in range(steps):
        slope, bend = -penalty * w, np.diag(penalty)
        for part, own in zip(_parts(len(x)), x.blocks(), strict=True):
            z = np.column_stack([(own - mean) / scale, np.ones(len(own))])
            p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
            slope += z.T @ (y[part] - p)
            bend += (z * (p * (1 - p))[:, None]).T @ z
        step = np.linalg.solve(bend, slope)
        w += step
        if np.abs(step).max() < 1e-6:
            break
    return w[:-1], float(w[-1]), mean, scale


def _vectors(keys: tuple[str, ...]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        wanted, first = {k: i for i, k in enumerate(keys)}, first_letters(keys)
        for batch in batches:
            place, value = [], []
            for text in batch.column(0):
                x = features(text.as_py(), wanted, first)
                at = np.flatnonzero(x)
                place.append(at.astype(np.uint16).tobytes())
                value.append(x[at].tobytes())
            yield pa.RecordBatch.from_arrays([batch.column(1), pa.array(place, pa.binary()), pa.array(value, pa.binary())], names=["class", "place", "value"])

    return run


def _matrix(texts: DataFrame, keys: tuple[str, ...]) -> tuple[np.ndarray, Rows]:
    """Class and features of every row of (text, class), a bounded sample, in an order of their own."""
    rows = sorted((r["class"], bytes(r["place"]), bytes(r["value"])) for r in texts.mapInArrow(_vectors(keys), "class int, place binary, value binary").collect())
    ends = np.cumsum([0, *[len(place) // 2 for _, place, _ in rows]])
    place, value = (np.frombuffer(b"".join(r[k] for r in rows), dtype=kind) for k, kind in ((1, np.uint16), (2, np.float64)))
    return np.array([r[0] for r in rows], dtype=np.int64), Rows(ends, place, value, len(keys) + 5)


def _remainder(doc_id) -> object:
    return F.crc32(doc_id.cast("string").cast("binary")) % 3


def _share(doc_id, wanted: int, there: int):
    """Whether an id is among about ``wanted`` of ``there`` rows, by its hash."""
    return F.pmod(F.xxhash64(doc_id), F.lit(1 << 40)) < int((1 << 40) * min(1.0, wanted / max(1, there)))


def labelled_sample(docs: DataFrame, labels: DataFrame, sample: int) -> tuple[DataFrame, dict[int, int]]:
    """(doc_id, text, class) of about ``sample`` labelled rows of each class at most, one for each id, and the usable labels of each class."""
    usable = labels.filter("toxic in (0, 1) and doc_id is not null").filter(_remainder(F.col("doc_id")) != 1).select("doc_id", F.col("toxic").cast("int").alias("class"))
    every = {r["class"]: r["n"] for r in usable.groupBy("class").agg(F.count("*").alias("n")).collect()}
    few = [usable.filter((F.col("class") == y) & _share(F.col("doc_id"), sample, every.get(y, 0))).groupBy("doc_id").agg(F.max("class").alias("class")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample) for y in (0, 1)]
    few = C.materialize(few[0].union(few[1]).groupBy("doc_id").agg(F.max("class").alias("class")), "labelled")
    texts = docs.select("doc_id", "text").join(F.broadcast(few), "doc_id")  # at most 2 * sample ids
    texts = texts.groupBy("doc_id", "class").agg(F.min(F.coalesce(F.col("text").cast("string"), F.lit(""))).alias("text"))
    return C.materialize(texts, "labelled-texts"), every


def unlabelled_sample(docs: DataFrame, labelled: DataFrame, rows: int) -> DataFrame:
    """(text, class): texts of at most ``rows`` documents that are neither held out nor in ``labelled``, class null."""
    free = docs.select("doc_id", F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).filter(F.col("doc_id").isNotNull() & (_remainder(F.col("doc_id")) != 1))
    free = free.join(F.broadcast(labelled.select("doc_id")), "doc_id", "left_anti").filter(_share(F.col("doc_id"), rows, 2 * docs.count() // 3))
    texts = free.groupBy("doc_id").agg(F.min("text").alias("text")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
    return C.materialize(texts.select("text", F.lit(None).cast("int").alias("class")), "model-texts")


def fit(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, model_rows: int = MODEL_ROWS) -> Model:
    """Lexicon from a sample of labelled rows, label model and classifier from documents without their labels."""
    texts, every = labelled_sample(docs, labels, sample)
    sizes = {r["class"]: r["n"] for r in texts.groupBy("class").agg(F.count("*").alias("n")).collect()}
    toxic, clean = sizes.get(1, 0), sizes.get(0, 0)
    if not toxic or not clean:
        return Model((), np.zeros(5), 30.0 if toxic else -30.0, np.zeros(5), np.ones(5))
    mined = texts.select("text", "class").mapInArrow(_mine, "entry string, toxic int, n long").groupBy("entry").agg(F.sum(F.expr("if(toxic = 1, n, 0)")).alias("n1"), F.sum(F.expr("if(toxic = 0, n, 0)")).alias("n0"))
    strong = mined.filter(f"n1 >= 3 and (n1 + 0.5) * {clean + 1} > 4 * (n0 + 0.5) * {toxic + 1}")  # what ``gain`` asks for; of a bounded sample
    keys = tuple(pick_keys(strong.toPandas(), toxic, clean))
    y, x = _matrix(texts.select("text", "class"), keys)
    known = x.votes(len(keys))
    expected = np.stack([(known[y == c].sum(axis=0) + 0.5) / ((y == c).sum() + 1) for c in (0, 1)])
    seen = unlabelled_sample(docs, texts, model_rows).withColumn("class", F.lit(0))
    _, free = _matrix(seen, keys)
    x = free if len(free) else x
    prior = every[1] / (every[0] + every[1])
    _, post = fit_label_model(x.votes(len(keys)), prior, expected)
    return Model(keys, *fit_linear(x, post))


def _score(model) -> object:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m: Model = model.value
        wanted, first = {k: i for i, k in enumerate(m.keys)}, first_letters(m.keys)
        for batch in batches:
            out = []
            for text in batch.column(batch.num_columns - 1):
                z = (features(text.as_py(), wanted, first) - m.mean) / m.scale
                out.append(float(1 / (1 + np.exp(-np.clip(z @ m.weights + m.bias, -30, 30)))))
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(out, pa.float64())], names=[*batch.schema.names[:-1], "toxicity_score"])

    return run


def score(docs: DataFrame, model: Model, text: str = "text", score_column: str = "toxicity_score", keep: list[str] | None = None) -> DataFrame:
    """``docs`` (or its columns ``keep``) with a score from 0 to 1."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    kept = docs.columns if keep is None else keep
    quoted = [F.col(f"`{c}`") for c in kept]
    places = [f"c{i}" for i in range(len(quoted))]  # names may clash
    wide = docs.select(*[c.alias(p) for c, p in zip(quoted, places, strict=True)], F.col(f"`{text}`").cast("string").alias("_text"))
    schema = T.StructType([*wide.schema.fields[:-1], T.StructField("toxicity_score", T.DoubleType())])
    return wide.mapInArrow(_score(shared), schema).toDF(*kept, score_column)


def op10_toxicity_weak(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Score of every document."""
    docs = C.table(spark, sf_dir, "documents").select("doc_id", "text")
    model = fit(docs, C.table(spark, sf_dir, "labels"))
    found = score(docs, model, keep=["doc_id"])
    held_out = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1
    return found.select("doc_id", F.coalesce(held_out, F.lit(False)).alias("held_out"), F.col("toxicity_score").alias("score"), F.when(F.col("toxicity_score") >= CUT, 1).otherwise(0).cast("int").alias("predicted"))
