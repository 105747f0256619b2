"""The texts of the mixing stage hold the very words of the blocks that the mix selects."""

import pytest

from mergecount.llm import common, mixing


@pytest.mark.parametrize("share", [0.8, 1.5])
def test_words_of_the_selected_blocks(spark, share):
    sizes = [(7 * i * i) % 150 + 1 for i in range(60)]
    docs = [(i, " ".join(f"d{i}w{j}" for j in range(n)), "en", "ab"[i % 2], 1) for i, n in enumerate(sizes)]
    df = spark.createDataFrame(docs, "doc_id long, text string, lang string, source string, n_chars long")
    mixed = common.materialize(mixing.mix(common.materialize(mixing.sized(df), "words"), share=share, places=True), "mixed")
    expected, partial, not_prefix = {}, 0, 0
    for r in mixed.collect():
        times = [((p // 32 + 1) * r["_q"] + r["_s"]) // r["_n"] - (p // 32 * r["_q"] + r["_s"]) // r["_n"] for p in range(r["_at"], r["_at"] + r["size"])]
        assert sum(times) == r["taken"]
        words = docs[r["doc_id"]][1].split()
        for turn in range(max(times, default=0)):
            own = [w for w, t in zip(words, times, strict=True) if t > turn]
            partial += len(own) < len(words)
            not_prefix += own != words[: len(own)]
            expected.setdefault(r["doc_id"], []).append(" ".join(own))
    got = {}
    for r in mixing.taken_texts(df, mixed).collect():
        got.setdefault(r["doc_id"], []).append(r["text"])
    assert partial > 5 and not_prefix > 2
    assert {k: sorted(v) for k, v in got.items()} == {k: sorted(v) for k, v in expected.items()}
