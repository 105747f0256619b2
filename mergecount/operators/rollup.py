"""Cubes and roll-ups by merging sketches: input rows are read once, grouping sets are unions of base sketches."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def grouping_sets(kind: str, dims: list[str]) -> list[tuple[str, ...]]:
    if kind == "cube":
        return [s for n in range(len(dims), -1, -1) for s in combinations(dims, n)]
    if kind == "rollup":
        return [tuple(dims[:n]) for n in range(len(dims), -1, -1)]
    raise ValueError("cube or rollup")


def expand(base: DataFrame, dims: list[str], sets: list[tuple[str, ...]]) -> DataFrame:
    """Each base sketch row once for every grouping set, with nulls for dimensions outside it and ``gid`` as in grouping_id()."""
    variants = F.array(*[F.struct(*[(F.col(d) if d in s else F.lit(None).cast(base.schema[d].dataType)).alias(d) for d in dims], F.lit(sum(1 << (len(dims) - 1 - i) for i, d in enumerate(dims) if d not in s)).alias("gid")) for s in sets])
    others = [c for c in base.columns if c not in dims]
    return base.select(*others, F.explode(variants).alias("_g")).select(*[F.col(f"_g.{d}").alias(d) for d in dims], F.col("_g.gid").alias("gid"), *others)


def merged_cells(base: DataFrame, dims: list[str], kind: str = "cube") -> DataFrame:
    """Cells (dims..., gid, tab, bin, level) of every grouping set from base cells."""
    wide = expand(base.select(*dims, "tab", "bin", "level"), dims, grouping_sets(kind, dims))
    return wide.groupBy(*dims, "gid", "tab", "bin").agg(F.max("level").alias("level"))


def merged_sketches(base: DataFrame, dims: list[str], seed, kind: str = "cube") -> DataFrame:
    """The same with packed sketches."""
    from .partial import merge_by

    return merge_by(expand(base.select(*dims, "sketch"), dims, grouping_sets(kind, dims)), seed, [*dims, "gid"])
