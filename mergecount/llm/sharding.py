"""Sharding by proportional stratified interleaving.

Rows of each source are put in a seeded order; a row at place r of n gets the fraction
(r + u) / n, u being a seeded start of its source in [0, 1). Starts differ, so that many small sources
don't crowd at one fraction, where one task would sort them all. Sorted by that fraction, every stretch of the whole order holds the sources in
their overall proportions, so equal cuts of it are shards that all match the mixture (each
source within about one row per shard of its share) and whose row counts differ by one at most.

Edge cases: a null source is a source of its own; a null text is empty; repeated rows are
dealt one by one (equal rows may swap places, which no output can show); an empty table gives
an empty result; extra columns are ignored by the query and kept by ``interleave``, whatever their
names (but for shard and slot, which it adds). Rows of one id (or none) are spread by their tie columns.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

SHARDS, SEED = 24, "interleave-7"


def interleave(rows: DataFrame, shards: int, seed: str = SEED, key: str = "doc_id", stratum: str = "source", tie: tuple[str, ...] = ()) -> DataFrame:
    """``rows`` with shard (int) and slot (long, gapless from 0 in each shard). ``rows`` should be slim and materialized."""
    total = rows.count()
    nb = C.bucket_count(total)
    shift = 60 - (nb.bit_length() - 1)
    ties = [F.col(f"`{c}`") for c in tie]
    keyed = rows.select(F.struct(*[F.col(f"`{c}`") for c in rows.columns]).alias("_in"), F.col(stratum).alias("_s"), F.col(key).alias("_key"), F.struct(F.lit(0), *ties).alias("_tie"), C.hash60(F.lit(seed), F.col(key), *ties).alias("_h"))
    keyed = keyed.withColumn("_k1", F.shiftright("_h", shift))
    order = [F.col("_h"), F.col("_key"), F.col("_tie")]
    start = C.hash60(F.lit(seed), F.lit("start"), F.coalesce(F.col("_s"), F.lit("")))
    sizes = keyed.groupBy("_s").agg(F.count(F.lit(1)).alias("_n")).withColumn("_u", F.shiftright(start, 28) / F.lit(float(1 << 32)))
    placed = C.prefix_sums(keyed, ["_s"], "_k1", order, {"_r": F.lit(1)}, sizes)
    placed = placed.withColumn("_f", (F.col("_r") + F.col("_u")) / F.col("_n")).withColumn("_k2", F.floor(F.col("_f") * nb))
    placed = C.materialize(placed.select("_in", "_s", "_key", "_tie", "_h", "_f", "_k2"), "fractions")
    whole = C.prefix_sums(placed, [], "_k2", [F.col("_f"), F.col("_s").asc_nulls_last(), *order], {"_g": F.lit(1)})
    shard = F.expr(f"_g * {shards} div {max(total, 1)}")
    begin = F.expr(f"((_g * {shards} div {max(total, 1)}) * {total} + {shards - 1}) div {shards}")
    return whole.select(*[F.col(f"_in.`{c}`").alias(c) for c in rows.columns], shard.cast("int").alias("shard"), (F.col("_g") - begin).alias("slot"))


def op7_stratified_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in shards 0 to 23 by the law ``rows``."""
    docs = C.table(spark, sf_dir, "documents")
    text = F.coalesce(F.col("text"), F.lit(""))
    slim = docs.select("doc_id", "source", (F.octet_length(text) + 8).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"))
    out = interleave(C.materialize(slim, "sizes"), SHARDS, tie=("text_crc32",))
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def _table_sql() -> str:
    table = []
    for byte in range(256):
        for _ in range(8):
            byte = (byte >> 1) ^ (0xEDB88320 if byte & 1 else 0)
        table.append(str(byte))
    return "[" + ",".join(table) + "]"


def oracle() -> str:
    """The same law with whole-table windows; CRC-32 is folded over the bytes."""
    return f"""
    with d as (select doc_id, source, coalesce(text, '') t from documents),
    b as (select doc_id, source, strlen(t) + 8 as size, t,
                 list_reduce(list_prepend(4294967295::BIGINT, list_transform(regexp_extract_all(hex(encode(t)), '..'), lambda x: ('0x' || x)::BIGINT)),
                   lambda c, x: xor(c >> 8, ({_table_sql()})[(xor(c, x) & 255) + 1])) c from d),
    h0 as (select doc_id, source, size, xor(c, 4294967295)::BIGINT as text_crc32 from b),
    h as (select *, ('0x' || substr(md5(concat_ws(':', '{SEED}', doc_id, text_crc32)), 1, 15))::BIGINT h, (('0x' || substr(md5(concat_ws(':', '{SEED}', 'start', coalesce(source, ''))), 1, 15))::BIGINT >> 28) / 4294967296.0::DOUBLE u from h0),
    r as (select *, ((row_number() over (partition by source order by h, doc_id, text_crc32) - 1) + u) / count(*) over (partition by source) f from h),
    g as (select *, row_number() over (order by f, source nulls last, h, doc_id, text_crc32) - 1 g, count(*) over () n from r)
    select doc_id, size::BIGINT size, text_crc32, 'rows' as law, (g * {SHARDS} // n)::INTEGER shard,
           (g - ((g * {SHARDS} // n) * n + {SHARDS - 1}) // {SHARDS})::BIGINT slot, null::INTEGER grown_shard from g"""
