"""Sketches as rows (group..., tab, bin, level): built, merged, cut and estimated by Spark alone.

Absent rows are empty cells. Levels are stored without the cut, so a merge is a union and a maximum,
which is partial before its only shuffle; the cut is a function of the merged levels.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..functions.native import NativeSeed, levels_and_bins

TOP = 64


def raw_cells(df: DataFrame, key: str, seed: NativeSeed, group: list[str] = (), repeated: bool = False) -> DataFrame:
    """Largest level of every cell. ``repeated``: keys stand in many rows; they are made distinct first (one slim shuffle) and hashed once."""
    if repeated:
        df = df.filter(F.col(key).isNotNull()).select(*group, key).distinct()
    return levels_and_bins(df, key, seed, list(group)).groupBy(*group, "tab", "bin").agg(F.max("level").alias("level"))


def union_all(*cells: DataFrame, group: list[str] = ()) -> DataFrame:
    """Merge of sketches in this form."""
    out = cells[0]
    for more in cells[1:]:
        out = out.unionByName(more)
    return out.groupBy(*group, "tab", "bin").agg(F.max("level").alias("level"))


def cut_curve(cells: DataFrame, group: list[str] = ()) -> DataFrame:
    """(group..., q, bits): cost of the cells for every cut, from a histogram of levels."""
    counts = cells.groupBy(*group, "level").agg(F.count("*").alias("n"))
    cuts = counts.withColumn("q", F.explode(F.sequence(F.lit(0), F.lit(TOP + 1))))
    left = F.greatest(F.col("level") - F.col("q"), F.lit(-1)) + 2
    width = sum((F.when(left >= 2**i, 1).otherwise(0) for i in range(1, 7)), F.lit(0))
    return cuts.groupBy(*group, "q").agg(F.sum(width * F.col("n")).alias("bits"))


def required_cut(cells: DataFrame, seed: NativeSeed, budget: float, group: list[str] = ()) -> DataFrame:
    """(group..., q): least cut that fits ``budget`` bits per cell."""
    limit = math.floor(budget * seed.l * seed.b)
    return cut_curve(cells, group).filter(F.col("bits") <= limit).groupBy(*group).agg(F.min("q").alias("q"))


def with_cut(cells: DataFrame, seed: NativeSeed, budget: float, group: list[str] = ()) -> DataFrame:
    """(group..., tab, bin, level, q): the state, level now counted from the cut; cells below it are gone."""
    q = required_cut(cells, seed, budget, group)
    # one row of q per group: the optimizer broadcasts it while it is small and shuffles it beyond
    joined = cells.join(q, list(group)) if group else cells.join(F.broadcast(q.limit(1)))
    return joined.select(*group, "tab", "bin", (F.col("level") - F.col("q")).cast("int").alias("level"), "q").filter("level >= 0")


def estimate(state: DataFrame, seed: NativeSeed, offset: int, group: list[str] = (), at: str = "estimate") -> DataFrame:
    """(group..., estimate, q): median over all l tables; a table that the cut has emptied counts as 0."""
    b, log_b = seed.b, seed.b.bit_length() - 1
    counts = state.groupBy(*group, "tab", (F.col("level") + F.col("q")).alias("_abs")).agg(F.count("*").alias("_n"), F.max("q").alias("q"))  # one row for each level: partial sums, whatever b is
    top = counts.groupBy(*group, "tab").agg(F.collect_list(F.struct("_abs", "_n")).alias("_all"), F.max("_abs").alias("_top"), F.max("q").alias("q"))
    s = F.greatest(F.lit(0), F.col("_top") - log_b + offset)
    hits = F.least(F.aggregate("_all", F.lit(0).cast("long"), lambda acc, x: acc + F.when(x["_abs"] >= F.col("_s"), x["_n"]).otherwise(0)), F.lit(b - 1))
    per_table = top.withColumn("_s", s).withColumn("_y", F.pow(F.lit(2.0), F.col("_s")) * F.log(1 - hits / F.lit(float(b))) / F.log(F.lit(1 - 1 / b)))
    found = per_table.groupBy(*group).agg(F.collect_list("_y").alias("_ys"), F.max("q").alias("q"))
    empty = F.array_repeat(F.lit(0.0), F.lit(seed.l) - F.size("_ys"))
    sorted_ys = F.array_sort(F.concat("_ys", empty))
    mid = (seed.l - 1) // 2
    value = (F.get(sorted_ys, F.lit(mid)) + F.get(sorted_ys, F.lit(seed.l // 2))) / 2
    return found.select(*group, F.round(value, 6).alias(at), F.col("q").cast("int").alias("q"))


def prune_for_estimate(cells: DataFrame, seed: NativeSeed, offset: int, group: list[str] = ()) -> DataFrame:
    """Cells at or above each table's threshold: the same estimates, also after merging with other pruned cells; not the full state."""
    top = cells.groupBy(*group, "tab").agg(F.greatest(F.lit(0), F.max("level") - (seed.b.bit_length() - 1) + offset).alias("_s"))
    return cells.join(top, [*group, "tab"]).filter("level >= _s").drop("_s")


def size_bits(state: DataFrame, seed: NativeSeed, group: list[str] = ()) -> DataFrame:
    """Exact bits of the gamma form of a state: every cell costs 2 floor(ld(level + 2)) + 1, an empty one 1."""
    v = F.col("level") + 2
    width = sum((F.when(v >= 2**i, 1).otherwise(0) for i in range(1, 7)), F.lit(0))
    return state.groupBy(*group).agg((F.sum(2 * width) + seed.l * seed.b).alias("cell_bits"))


def two_pass_cells(df: DataFrame, key: str, seed: NativeSeed, offset: int, group: list[str] = ()) -> DataFrame:
    """Cells at or above each table's threshold in two passes: the largest levels first, then only rows that reach them."""
    rows = levels_and_bins(df, key, seed, list(group))
    top = rows.groupBy(*group, "tab").agg(F.greatest(F.lit(0), F.max("level") - (seed.b.bit_length() - 1) + offset).alias("_s"))
    return rows.join(top, [*group, "tab"]).filter("level >= _s").groupBy(*group, "tab", "bin").agg(F.max("level").alias("level"))


def prefix_merges(cells_by_step: DataFrame, step: str, last: int, group: list[str] = ()) -> DataFrame:
    """Cells of all steps up to each, for integer steps up to ``last``.

    A running maximum for each cell, of which only the steps that raise it are kept; each of these stands
    for all steps until the next one. Nothing is aggregated again, and what is written out is the result.
    """
    by = W.partitionBy(*group, "tab", "bin").orderBy(step)
    before = F.max("level").over(by.rowsBetween(W.unboundedPreceding, -1))
    raised = cells_by_step.withColumn("_before", before).filter("_before is null or level > _before")
    until = F.coalesce(F.lead(step).over(by) - 1, F.lit(last))
    return raised.withColumn("_until", until).select(*group, F.explode(F.sequence(F.col(step), F.col("_until"))).alias(step), "tab", "bin", "level")
