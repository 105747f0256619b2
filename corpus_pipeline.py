"""Corpus pipeline: toxicity, near-duplicates, personal data, mixing and packing of documents.

Each stage is a function of (spark, docs, sf_dir) that works on all rows its predecessor kept and
returns the columns of ``documents`` (the last: packed pieces). ``run`` writes every stage's rows to
the shared folder and reads them again as the next one's input.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mergecount.llm import common, mixing, packing, pii, simhash, toxicity

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity score is below the cut; the model is learned from their labels."""
    model = toxicity.fit(docs, common.table(spark, sf_dir, "labels"))
    common.release(spark)
    scored = toxicity.score(docs.select(*COLUMNS), model)
    return scored.filter(F.col("toxicity_score") < toxicity.CUT).select(*COLUMNS)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of every group of near-duplicates one document, that with the smallest id (a missing id is the largest)."""
    return simhash.survivors(docs.select(*COLUMNS))


def pii_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with pseudonyms in place of personal data."""
    hidden = pii.pseudonymize(docs.select(*COLUMNS), pii.key_of(spark), found="_replaced")
    return hidden.select("doc_id", "text", "lang", "source", F.when(F.col("_replaced") > 0, F.length("text")).otherwise(F.col("n_chars")).cast("long").alias("n_chars"))


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix: of every document the words of the blocks that it takes, in order (those taken twice stand in two rows)."""
    rows = common.numbered(docs.select(*COLUMNS), "mix-rows")
    sizes = common.materialize(mixing.sized(rows, "_row"), "words")
    common.release(spark)
    return mixing.taken_texts(rows, mixing.mix(sizes, places=True), on="_row").select(*COLUMNS)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the documents in sequences of at most 4096 tokens."""
    return packing.pack(docs, with_ids=False)


STAGES = [("toxicity", toxicity_stage), ("near-duplicates", near_duplicate_stage), ("pii", pii_stage), ("mixing", mixing_stage), ("packing", packing_stage)]

#: The toxicity model and the tokenizer have no SQL form; tests hold run() against a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = common.materialize(docs, f"stage-{name}", "snappy")
    return docs
