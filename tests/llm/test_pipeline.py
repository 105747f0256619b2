"""The pipeline against plain versions of its stages, none of which uses the library's own result."""

import re

import duckdb
import pytest

import corpus_pipeline as cp
from mergecount.llm import common, mixing, packing, pii, toxicity
from tests.llm.test_pii import plain
from tests.llm.test_toxicity import literal_score

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def words_of(text):
    return [w for w in re.split(r"[\x20\x09-\x0d]+", text or "") if w]


def shingles(text):
    w = words_of("".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    size = min(5, len(w))
    return {tuple(w[i : i + size]) for i in range(len(w) - size + 1)} if w else set()


def components(rows):
    """Place of the first document of each component by all pairs: (id missing, id, place) of rows (doc_id, text)."""
    sets = [shingles(t) for _, t in rows]
    root = list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            a, b = sets[i], sets[j]
            both = len(a & b)
            if (not a and not b) or (a and b and both >= 0.8 * (len(a) + len(b) - both)):
                root[find(i)] = find(j)
    least = {}
    for i, (doc_id, _) in enumerate(rows):
        key = (doc_id is None, doc_id or 0, i)
        least[find(i)] = min(least.get(find(i), key), key)
    return sorted(least.values())


@pytest.fixture(scope="module")
def stages(spark, sf):
    """Rows of every stage over the given table."""
    docs, kept = common.table(spark, sf, "documents"), {}
    kept["documents"] = docs
    for k, (name, stage) in enumerate(cp.STAGES):
        docs = common.materialize(stage(spark, docs, sf), f"test-{k}")
        kept[name] = docs
        if name != "packing":
            assert docs.columns == list(cp.COLUMNS)
    return kept


def test_toxicity(spark, sf, stages):
    docs = stages["documents"]
    model = toxicity.fit(docs, common.table(spark, sf, "labels"))
    expected = sorted(r["doc_id"] for r in docs.collect() if literal_score(r["text"], model) < 0.7)
    assert sorted(r["doc_id"] for r in stages["toxicity"].collect()) == expected


def test_near_duplicates(stages):
    rows = [(r["doc_id"], r["text"]) for r in stages["toxicity"].collect()]
    assert sorted(r["doc_id"] for r in stages["near-duplicates"].collect()) == [doc_id for _, doc_id, _ in components(rows)]


def test_pseudonyms(spark, stages):
    before = {r["doc_id"]: r for r in stages["near-duplicates"].collect()}
    pattern, key = re.compile(pii.PATTERN, re.ASCII), pii.key_of(spark)
    after = stages["pii"].collect()
    assert len(after) == len(before)
    for r in after:
        old = before[r["doc_id"]]
        assert r["text"] == pattern.sub(lambda m: plain(m[0], key), old["text"]) and (r["lang"], r["source"]) == (old["lang"], old["source"])


def test_mixing(stages):
    """Words taken by SQL that writes out all quotients; texts are the documents' words in order."""
    con = duckdb.connect()
    con.register("documents", stages["pii"].toPandas())
    taken = {i: n for i, n in con.sql(f"select doc_id, taken from ({mixing.oracle()})").fetchall() if n}
    whole = {r["doc_id"]: words_of(r["text"]) for r in stages["pii"].collect()}
    got = {}
    for r in stages["mixing"].collect():
        words = words_of(r["text"])
        got[r["doc_id"]] = got.get(r["doc_id"], 0) + len(words)
        rest = iter(whole[r["doc_id"]])
        assert all(w in rest for w in words)
    assert got == taken


def test_packing(stages):
    tok = packing.WordTokenizer(packing.tokenizer_definition()).tokenizer
    lengths = sorted(len(tok.encode(r["text"], add_special_tokens=False).ids) + 1 for r in stages["mixing"].collect())
    spans, sizes = {}, {}
    for r in stages["packing"].collect():
        spans.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
        sizes[r["doc_tokens"]] = sizes.get(r["doc_tokens"], 0) + r["length"]
    assert sum(n for s in spans.values() for _, n in s) == sum(lengths)
    assert all(sizes[n] == n * lengths.count(n) for n in set(lengths))
    for k, own in spans.items():
        own.sort()
        assert own[0][0] == 0 and all(a + b == c for (a, b), (c, _) in zip(own, own[1:], strict=False))
        assert sum(n for _, n in own) == 4096 or k == max(spans)


ODD = [
    (1, None, None, None, None), (2, "", "en", None, 0), (3, "a b c", "en", "s", 5), (3, "a b c", "en", "s", 5), (3, "another text of this id stays too", "en", "s", 33),
    (None, "a text without an id that is clean", "en", "s", 34), (None, "a text without an id that is clean", "en", "s", 34), (None, "and one more without an id", None, "t", 26),
]


def test_odd_rows_stay(spark, sf):
    """Rows without an id, and several texts of one id, go through all stages; copies go."""
    rows = spark.createDataFrame(ODD, SCHEMA)
    for k, (name, stage) in enumerate(cp.STAGES):
        rows = common.materialize(stage(spark, rows, sf), f"odd-{k}")
        if name in ("near-duplicates", "pii"):
            assert sorted(str((r["doc_id"], r["text"])) for r in rows.collect()) == sorted(str(x) for x in [(1, None), (3, "a b c"), (3, ODD[4][1]), (None, ODD[5][1]), (None, ODD[7][1])])
    assert None in {r["doc_id"] for r in rows.collect()}  # the mix takes blocks of 32 words, so not every short text


def test_empty_input(spark, sf):
    rows = spark.createDataFrame([], SCHEMA)
    for k, (_, stage) in enumerate(cp.STAGES):
        rows = common.materialize(stage(spark, rows, sf), f"empty-{k}")
        assert rows.count() == 0
