"""Earlier distinct counters, as relations: bit pattern, largest level, binned levels, exact, built-in, sampling."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.native import NativeSeed, ideal_levels_and_bins, levels_and_bins
from ..operators import cells

#: Fixed value: correction of the mean position of the lowest unset bit.
PHI = 0.77351


def exact(df: DataFrame, key: str, group: list[str] = ()) -> DataFrame:
    return df.groupBy(*group).agg(F.countDistinct(key).alias("distinct"))


def exact_bitmap(df: DataFrame, key: str) -> DataFrame:
    """Exact count of non-negative integers with the built-in bitmaps: one bitmap for each bucket of positions."""
    rows = df.filter(F.col(key).isNotNull()).select(F.col(key).cast("long").alias("_k"))
    buckets = rows.groupBy(F.expr("bitmap_bucket_number(_k)").alias("bucket")).agg(F.expr("bitmap_construct_agg(bitmap_bit_position(_k))").alias("bits"))
    return buckets.agg(F.sum(F.expr("bitmap_count(bits)")).alias("distinct"))


def bit_pattern_cells(df: DataFrame, key: str, seed: NativeSeed, group: list[str] = (), ideal: bool = False) -> DataFrame:
    """(group..., tab, bin, pattern): OR of one bit per level (levels over 62 count as 62). Merges by OR."""
    rows = ideal_levels_and_bins(df, key, seed.l, seed.b, list(group)) if ideal else levels_and_bins(df, key, seed, list(group))
    return rows.groupBy(*group, "tab", "bin").agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), F.least("level", F.lit(62)))).alias("pattern"))


def bit_pattern(df: DataFrame, key: str, seed: NativeSeed, group: list[str] = (), ideal: bool = False) -> DataFrame:
    """Oldest counter: the mean position of the lowest unset bit over the bins of table 0 (absent bins count 0).

    It assumes ideal hash functions: ``ideal`` takes xxHash for them, else pairwise maps that SQL can repeat stand in.
    """
    patterns = bit_pattern_cells(df, key, NativeSeed(1, seed.b, seed.entropy), group, ideal)
    lowest = F.bit_count(F.col("pattern").bitwiseAND(F.lit(-1).cast("long").bitwiseXOR(F.col("pattern") + 1)))
    total = patterns.groupBy(*group).agg(F.sum(lowest).alias("_sum"))
    return total.select(*group, F.round(seed.b / PHI * F.pow(F.lit(2.0), F.col("_sum") / seed.b), 6).alias("estimate"))


def max_level(df: DataFrame, key: str, seed: NativeSeed, group: list[str] = ()) -> DataFrame:
    """Pairwise counter of constant factor: 2 to the largest level of each table, and their median."""
    tops = levels_and_bins(df, key, seed, list(group)).groupBy(*group, "tab").agg(F.max("level").alias("top"))
    return tops.groupBy(*group).agg(F.round(F.median(F.pow(F.lit(2.0), F.col("top"))), 6).alias("estimate"))


def binned_levels(df: DataFrame, key: str, seed: NativeSeed, group: list[str] = ()) -> DataFrame:
    """Binned levels without a cut; a rough count (median of the tables' largest levels) sets the threshold at the end."""
    raw = cells.raw_cells(df, key, seed, group)
    tops = raw.groupBy(*group, "tab").agg(F.max("level").alias("_top"))
    rough = tops.groupBy(*group).agg(F.floor(F.median("_top")).cast("int").alias("_rough"))
    log_b = seed.b.bit_length() - 1
    joined = raw.join(rough, list(group)) if group else raw.join(F.broadcast(rough.limit(1)))
    at = joined.withColumn("_s", F.greatest(F.lit(0), F.col("_rough") - log_b + 1))
    hit = at.groupBy(*group, "tab", "_s").agg(F.sum(F.when(F.col("level") >= F.col("_s"), 1).otherwise(0)).alias("_p"))
    p = F.least("_p", F.lit(seed.b - 1))
    y = F.pow(F.lit(2.0), F.col("_s")) * F.log(1 - p / F.lit(float(seed.b))) / F.log(F.lit(1 - 1 / seed.b))
    return hit.withColumn("_y", y).groupBy(*group).agg(F.round(F.median("_y"), 6).alias("estimate"))


def built_in(df: DataFrame, key: str, group: list[str] = (), rsd: float = 0.02, lg_k: int = 12) -> DataFrame:
    """Engineering yardsticks: Spark's own approximate counts."""
    return df.groupBy(*group).agg(
        F.approx_count_distinct(key, rsd).alias("hll_plus"),
        F.hll_sketch_estimate(F.hll_sketch_agg(key, F.lit(lg_k))).alias("hll_sketch"),
        F.expr(f"theta_sketch_estimate(theta_sketch_agg({key}, {lg_k}))").alias("theta"),
    )


def sampling(df: DataFrame, key: str, share: float, seed: int = 7, rows_by: list[str] = ()) -> DataFrame:
    """Extrapolates the distinct keys of a row sample as if all keys were equally frequent; fails on skewed keys.

    Rows are picked by a hash of the columns ``rows_by`` (all of them by default), so another layout of the input picks the same.
    """
    one = F.xxhash64(*(rows_by or df.columns), F.lit(seed))
    rows = df.filter(F.col(key).isNotNull()).filter(F.pmod(one, F.lit(1_000_000)) < int(share * 1_000_000))
    counts = rows.groupBy(key).agg(F.count("*").alias("n"))
    stats = counts.agg(F.count("*").alias("found"), F.sum(F.when(F.col("n") == 1, 1).otherwise(0)).alias("once"), F.sum("n").alias("rows"))
    return stats.select("found", "once", (F.col("found") / (1 - (1 - F.lit(share)) * F.col("once") / F.greatest(F.col("rows"), F.lit(1)))).alias("estimate"))
