"""Mixing sources to target weights by Sainte-Lague apportionment, with built-in functions only.

Targets: sources by code point (null last) weigh 3, 1, 2, repeating, and share ``SHARE`` times all
words; a target stops at ``CAP`` times its source's words and the excess is shared again by weight
until none is above. Blocks of ``BLOCK`` words are seats: a source with target t offers the quotients
t, t/3, t/5, ... and the highest quotients of all sources win. Each source's seats go to its ``SHARDS``
shards (hash ranges of documents) in the same way, by the shard's words, so every shard has an integer
quota; the number of shards is a parameter and the law is one at every size. Inside a shard the documents stand in seeded order as one run of words, cut in blocks; a
quota of q among n blocks takes each block floor(q/n) or ceil(q/n) times, evenly from a seeded start.

Quotas never exceed ``CAP`` times the blocks there are, so no word is taken more than twice. Taken
words differ from a target by part of a block for each shard.

Edge cases: a null source is a source; null and empty texts have size 0 and take 0; repeated rows
count each; with no words at all every target is 0; an empty table gives an empty result; extra
columns are kept, whatever their names. The table of sources (a row each) is ranked in one task, and a
source's shards are one small array; documents are never gathered by source: they are dealt by hash
range of id and size, so rows of one id (or none) that differ in size are spread too.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from . import common as C

WEIGHTS, SHARE, CAP, BLOCK, SHARDS, SEED = (3, 1, 2), 1.5, 2, 32, 16, "mix-5"
PLACES = ("_at", "_s", "_q", "_n")


def words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(C.WORD)), F.lit(0)).cast("long")


def targets(sources: DataFrame, share: float = SHARE, cap: float = CAP, weights: tuple[float, ...] = WEIGHTS) -> DataFrame:
    """Adds no (1, 2, ... by code point, null last), weight and target to (source, source_size)."""
    everything = W.partitionBy()
    no = F.row_number().over(W.orderBy(F.col("source").asc_nulls_last()))
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), F.pmod(F.col("no") - 1, F.lit(len(weights))) + 1)
    rows = sources.withColumn("no", no).withColumn("weight", weight).withColumn("_cap", F.col("source_size") * float(cap))
    by_ratio = W.orderBy(F.col("_cap") / F.col("weight"), "no").rowsBetween(W.unboundedPreceding, -1)
    full = F.coalesce(F.sum("_cap").over(by_ratio), F.lit(0.0))
    open_weight = F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(by_ratio), F.lit(0.0))
    rows = rows.withColumn("_rate", (F.sum("source_size").over(everything) * float(share) - full) / open_weight)
    # The first source, by cap over weight, that the rate of its turn does not fill sets the rate of all that follow.
    level = F.min(F.when(F.col("_rate") * F.col("weight") <= F.col("_cap"), F.struct((F.col("_cap") / F.col("weight")).alias("at"), F.col("no").alias("no"), F.col("_rate").alias("rate")))).over(everything)["rate"]
    target = F.least(F.col("_cap"), F.coalesce(level, F.lit(float("inf"))) * F.col("weight"))
    return rows.select("source", "source_size", "no", "weight", target.alias("target"))


def apportion(parts: DataFrame, group: list[str], seats: str, item: str, votes: str, most: str) -> DataFrame:
    """Sainte-Lague seats for the items of each group, none above ``most``.

    (group..., item, _seats): the ``seats`` highest quotients votes/(2k+1), k < most; ties go to the
    higher quotient's smaller item. The quotient of the last seat is found by bisection.
    """
    entry = F.struct(F.col(item).alias("i"), F.col(votes).cast("double").alias("v"), F.col(most).cast("long").alias("m"))
    lists = parts.groupBy(*group).agg(F.max(seats).alias("_k"), F.max(F.col(votes).cast("double")).alias("_hi"), F.collect_list(entry).alias("_items"))
    given = lambda x, d: F.least(x["m"], F.floor(x["v"] / d + 0.5))

    def halve(acc: Column, _: Column) -> Column:
        mid = (acc["lo"] + acc["hi"]) / 2
        fits = F.aggregate(F.col("_items"), F.lit(0).cast("long"), lambda a, x: a + given(x, mid)) <= F.col("_k")
        return F.when(fits, F.struct(acc["lo"].alias("lo"), mid.alias("hi"))).otherwise(F.struct(mid.alias("lo"), acc["hi"].alias("hi")))

    start = F.struct(F.lit(0.0).alias("lo"), (F.col("_hi") * 2 + 1).alias("hi"))
    rows = lists.withColumn("_d", F.aggregate(F.sequence(F.lit(1), F.lit(100)), start, halve)["hi"])
    rows = rows.select(*group, "_k", "_d", F.explode("_items").alias("_x")).withColumn("_base", given(F.col("_x"), F.col("_d")))
    w = W.partitionBy(*group)
    left = F.col("_k") - F.sum("_base").over(w)
    can = F.col("_base") < F.col("_x.m")
    turn = F.row_number().over(w.orderBy(can.desc(), (F.col("_x.v") / (F.col("_base") * 2 + 1)).desc(), F.col("_x.i")))
    return rows.select(*group, F.col("_x.i").alias(item), (F.col("_base") + F.when(can & (turn <= left), 1).otherwise(0)).alias("_seats"))


def mix(sizes: DataFrame, share: float = SHARE, cap: int = CAP, block: int = BLOCK, seed: str = SEED, key: str = "doc_id", shards: int = SHARDS, places: bool = False) -> DataFrame:
    """``sizes`` (key, source, size and others, slim and materialized) with source_size, target and taken.

    ``shards`` (a power of two) is a parameter of the law, whatever the number of rows. ``places`` adds what
    tells the blocks taken: _at (words before the document), _s, _q and _n (start, quota and number of blocks).
    """
    nb = C.bucket_count(sizes.count())
    shard_bits = shards.bit_length() - 1
    fine_bits = max(shard_bits, nb.bit_length() - 1)
    rows = sizes.select(F.struct(*[F.col(f"`{c}`") for c in sizes.columns]).alias("_in"), F.col("source").alias("_source"), F.col(key).alias("_key"), F.col("size").alias("_size"))
    rows = rows.withColumn("_h", C.hash60(F.lit(seed), F.col("_key"), F.col("_size")))
    rows = rows.withColumn("_fine", F.shiftright("_h", 60 - fine_bits)).withColumn("_shard", F.shiftright("_h", 60 - shard_bits))

    cells = C.materialize(rows.groupBy("_source", "_shard").agg(F.sum("_size").alias("_words")), "cells")
    sources = C.materialize(targets(cells.groupBy(F.col("_source").alias("source")).agg(F.sum("_words").alias("source_size")), share, cap), "targets")
    blocks = lambda c: F.ceil(F.col(c) / block)
    seats = sources.withColumn("_all", F.lit(1)).withColumn("_most", blocks("source_size") * cap).withColumn("_wanted", F.round(F.sum("target").over(W.partitionBy()) / block).cast("long"))
    won = apportion(seats, ["_all"], "_wanted", "no", "target", "_most").select("no", F.col("_seats").alias("_quota"))
    per_source = sources.join(won, "no").withColumnRenamed("source", "_of")
    parts = cells.join(per_source, F.col("_source").eqNullSafe(F.col("_of"))).withColumn("_most", blocks("_words") * cap)
    quota = apportion(parts, ["no"], "_quota", "_shard", "_words", "_most").select("no", "_shard", F.col("_seats").alias("_q"))
    quota = C.materialize(parts.join(quota, ["no", "_shard"]).select("_source", "_shard", "_words", "_q", "source_size", "target"), "shards")

    placed = C.prefix_sums(rows, ["_source", "_shard"], "_fine", [F.col("_h"), F.col("_key"), F.col("_size")], {"_at": F.col("_size")}, quota)
    placed = placed.withColumn("_n", F.greatest(F.lit(1).cast("long"), F.expr(f"(_words + {block - 1}) div {block}")))
    start = F.pmod(C.hash60(F.lit(seed), F.lit("start"), F.coalesce(F.col("_source"), F.lit("")), F.col("_shard")), F.col("_n"))
    placed = placed.withColumn("_s", start).withColumn("_end", F.col("_at") + F.col("_size"))
    upto = lambda k: f"((({k}) * _q + _s) div _n - _s div _n)"
    words_before = lambda x: f"({block} * {upto(f'{x} div {block}')} + ({x} % {block}) * ({upto(f'{x} div {block} + 1')} - {upto(f'{x} div {block}')}))"
    taken = F.expr(f"{words_before('_end')} - {words_before('_at')}")
    kept = [F.col(f"_in.`{c}`").alias(c) for c in sizes.columns]
    return placed.select(*kept, F.col("source_size").cast("long").alias("source_size"), F.col("target").cast("double").alias("target"), taken.cast("long").alias("taken"), *(PLACES if places else ()))


def _div(a: Column, b: Column) -> Column:
    """Quotient of two whole numbers that are not negative, exact at any size."""
    return F.call_function("div", a, b)


def sized(docs: DataFrame, *more: str) -> DataFrame:
    return docs.select("doc_id", "source", words(F.col("text")).alias("size"), *more)


def taken_texts(docs: DataFrame, mixed: DataFrame, block: int = BLOCK, on: str = "doc_id") -> DataFrame:
    """``docs`` as the mix takes them: a row for each whole copy, and one with the words of the blocks that are taken once more.

    ``mixed`` is a mix with places; without them the words taken once more are the first ones. Documents of
    which nothing is taken are left out. ``on`` names the column that tells one document of both from the next
    (give them a row number where ids may be null or repeated); the result has it no more if it is not doc_id.
    """
    placed = all(c in mixed.columns for c in PLACES)
    one = F.max(F.struct("taken", "size", *(PLACES if placed else ()))).alias("_m")
    what = C.materialize(mixed.filter("taken > 0").groupBy(F.col(on).alias("_id")).agg(one).select("_id", "_m.*"), "taken")
    what = what.select("_id", *[F.col(c).alias(f"_mix{c}") for c in what.columns[1:]])
    joined = docs.join(what.hint("merge"), docs[on] == F.col("_id"))  # grows with the documents: never broadcast
    # All blocks are taken _q div _n times, some once more; without places whole copies come first.
    whole = F.expr("_mix_q div _mix_n" if placed else "_mixtaken div _mixsize")
    rest = F.col("_mixtaken") - whole * F.col("_mixsize")
    found = F.regexp_extract_all("text", F.lit("[\\x20\\x09-\\x0D]*" + C.WORD), F.lit(0))

    def chosen(words: Column) -> Column:
        if not placed:
            return F.slice(words, F.lit(1), rest.cast("int"))
        at, size, s, q, n = (F.col(f"_mix{c}") for c in ("_at", "size", "_s", "_q", "_n"))
        more = lambda k: _div(k * F.pmod(q, n) + s, n)
        blocks = F.filter(F.sequence(_div(at, F.lit(block)), _div(at + size - 1, F.lit(block))), lambda k: more(k + 1) > more(k))

        def cut(k: Column) -> Column:
            first, end = F.greatest(k * block - at, F.lit(0)), F.least((k + 1) * block - at, size)
            return F.slice(words, (first + 1).cast("int"), (end - first).cast("int"))

        return F.flatten(F.transform(blocks, cut))

    # A lambda's variable, so that the words are found once for all blocks.
    begun = F.transform(F.array(found), lambda words: F.array_join(chosen(words), ""))
    begun = F.transform(begun, lambda t: F.regexp_replace(t, "^[\\x20\\x09-\\x0D]+", "")) if placed else begun
    nothing = F.array().cast("array<string>")
    full = (whole + F.when(rest == F.col("_mixsize"), 1).otherwise(0)).cast("int")
    copies = F.concat(F.array_repeat("text", full), F.when((rest > 0) & (rest < F.col("_mixsize")), begun).otherwise(nothing))
    rows = joined.withColumn("_copy", F.explode_outer(copies)).filter("_copy is not null")  # outer: an inferred filter would make the copies twice
    length = F.when(F.col("_copy") == F.col("text"), F.col("n_chars")).otherwise(F.length("_copy")).cast("long")
    new = {"text": F.col("_copy"), "n_chars": length}
    return rows.select(*[new.get(c, F.col(c)).alias(c) for c in docs.columns if c == "doc_id" or c != on])


def op5_apportioned_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The words that the mix takes of every document."""
    sizes = C.materialize(sized(C.table(spark, sf_dir, "documents")), "words")
    return mix(sizes).select("doc_id", "size", "source_size", "target", "taken")


def oracle() -> str:
    """Literal form: targets by repeated sharing, all quotients of sources and of shards written out and ranked."""
    up = lambda k: f"((({k}) * q + s) // n - s // n)"
    before = lambda x: f"({BLOCK} * {up(f'{x} // {BLOCK}')} + ({x} % {BLOCK}) * ({up(f'{x} // {BLOCK} + 1')} - {up(f'{x} // {BLOCK}')}))"
    shift = 60 - (SHARDS.bit_length() - 1)
    return f"""
    with recursive d0 as (select doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+'))::BIGINT size from documents),
    d as (select *, ('0x' || substr(md5(concat_ws(':', '{SEED}', doc_id, size)), 1, 15))::BIGINT h from d0),
    s0 as (select source, sum(size)::BIGINT source_size, row_number() over (order by source nulls last) no from d group by source),
    s1 as (select *, [3.0, 1.0, 2.0][(no - 1) % 3 + 1]::DOUBLE w, {CAP}.0 * source_size cap, {SHARE} * sum(source_size) over () pot from s0),
    fill as (select 0 turn, no, w, cap::DOUBLE cap, pot::DOUBLE pot, false as is_full from s1
      union all
      select turn + 1, no, w, cap, pot, is_full or w * (pot - sum(case when is_full then cap else 0 end) over ()) / nullif(sum(case when is_full then 0 else w end) over (), 0) > cap from fill where turn < 60),
    t as (select no, case when is_full then cap else w * (pot - sum(case when is_full then cap else 0 end) over ()) / nullif(sum(case when is_full then 0 else w end) over (), 0) end target from fill where turn = 60),
    k as (select t.no, target, unnest(range(0, least(ceil(source_size / {BLOCK}) * {CAP}, ceil(target / {BLOCK}) + 50)::BIGINT)) j from t join s1 using (no)),
    kk as (select no, j, target / (2 * j + 1) quotient, (select round(sum(target) / {BLOCK}) from t) seats from k),
    won as (select no, count(*) seats from (select no, seats, row_number() over (order by quotient desc, no) r from kk) where r <= seats group by no),
    e as (select d.*, no, source_size, h >> {shift} shard from d join s1 on d.source is not distinct from s1.source),
    c as (select no, shard, sum(size)::BIGINT words from e group by all),
    ck as (select no, shard, words, unnest(range(0, (ceil(words / {BLOCK}) * {CAP})::BIGINT)) j from c),
    got as (select no, shard, count(*) q from (select no, shard, row_number() over (partition by no order by words / (2 * j + 1) desc, shard) r from ck) join won using (no) where r <= seats group by all),
    p as (select e.*, target, coalesce(q, 0) q, greatest(1, (words + {BLOCK - 1}) // {BLOCK})::BIGINT n,
      coalesce(sum(size) over (partition by no, shard order by h, doc_id, size rows between unbounded preceding and 1 preceding), 0)::BIGINT a
      from e join t using (no) join c using (no, shard) left join got using (no, shard)),
    z as (select *, a + size b, (('0x' || substr(md5(concat_ws(':', '{SEED}', 'start', coalesce(source, ''), shard)), 1, 15))::BIGINT % n) s from p)
    select doc_id, size, source_size, target, ({before('b')} - {before('a')})::BIGINT taken from z"""
