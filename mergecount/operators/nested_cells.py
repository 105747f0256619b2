"""The nested sketch in row form: cells with a copy number, a cut per (group, copy)."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.native import NativeSeed, levels_and_bins
from . import cells


@dataclass(frozen=True)
class NestedNativeSeed:
    """m copies of l tables; the hash tables of all copies are read in one pass."""

    l: int  # noqa: E741
    b: int
    m: int
    entropy: int | str

    def flat(self) -> NativeSeed:
        return NativeSeed(self.l * self.m, self.b, self.entropy)

    def inner(self) -> NativeSeed:
        return NativeSeed(self.l, self.b, self.entropy)


def raw_cells(df: DataFrame, key: str, seed: NestedNativeSeed, group: list[str] = (), repeated: bool = False) -> DataFrame:
    """Largest level of every cell of every copy, all from one scan. ``repeated``: as in ``cells.raw_cells``."""
    if repeated:
        df = df.filter(F.col(key).isNotNull()).select(*group, key).distinct()
    flat = levels_and_bins(df, key, seed.flat(), list(group))
    split = flat.select(*group, F.floor(F.col("tab") / seed.l).cast("int").alias("copy"), F.pmod("tab", F.lit(seed.l)).alias("tab"), "bin", "level")
    return split.groupBy(*group, "copy", "tab", "bin").agg(F.max("level").alias("level"))


def estimate(df: DataFrame, key: str, seed: NestedNativeSeed, budget: float, offset: int, group: list[str] = (), repeated: bool = False) -> DataFrame:
    """(group..., estimate): median over copies of the medians over tables."""
    raw = raw_cells(df, key, seed, group, repeated)
    state = cells.with_cut(raw, seed.inner(), budget, [*group, "copy"])
    inner = cells.estimate(state, seed.inner(), offset, [*group, "copy"], "inner")
    return inner.groupBy(*group).agg(F.round(F.median("inner"), 6).alias("estimate"))
