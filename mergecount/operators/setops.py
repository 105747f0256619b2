"""Set operations on keys: union by merge, others by inclusion and exclusion, and exact yardsticks."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sketch import Sketch


def union_estimate(a: Sketch, b: Sketch) -> float:
    return Sketch(a.context, a.levels.copy(), a.q).merge(b).estimate().value


def intersection_estimate(a: Sketch, b: Sketch) -> tuple[float, float]:
    """Estimate and the absolute error that an error of one per cent in each part can add to it."""
    x, y, u = a.estimate().value, b.estimate().value, union_estimate(a, b)
    return max(0.0, x + y - u), 0.01 * (x + y + u)


def difference_estimate(a: Sketch, b: Sketch) -> tuple[float, float]:
    u, y = union_estimate(a, b), b.estimate().value
    return max(0.0, u - y), 0.01 * (u + y)


def overlap(seed, a: bytes, b: bytes) -> tuple[float, float, float]:
    """Estimated sizes of the intersection, of what only the first has, and of the union of two packed sketches."""
    from .partial import _unpack

    value = lambda s: s.estimate() if isinstance(s.estimate(), float) else s.estimate().value
    x, y = value(_unpack(seed, a)), value(_unpack(seed, b))
    u = value(_unpack(seed, a).merge(_unpack(seed, b)))
    return max(0.0, x + y - u), max(0.0, u - y), u


def set_estimates(pairs: DataFrame, seed, a: str = "a", b: str = "b") -> DataFrame:
    """``pairs`` of stored sketches (columns ``a`` and ``b``) with in_both, only_a, only_b and in_either, by inclusion and exclusion.

    ``slack``: what an error of one per cent in each part can add to a difference.
    """
    @F.pandas_udf("in_both double, only_a double, only_b double, in_either double, slack double")
    def found(left: pd.Series, right: pd.Series) -> pd.DataFrame:
        rows = []
        for x, y in zip(left, right, strict=True):
            both, only_a, u = overlap(seed, bytes(x), bytes(y))
            only_b = overlap(seed, bytes(y), bytes(x))[1]
            rows.append((both, only_a, only_b, u, 0.01 * (2 * u + both)))
        return pd.DataFrame(rows, columns=["in_both", "only_a", "only_b", "in_either", "slack"])

    return pairs.withColumn("_s", found(a, b)).select(*[c for c in pairs.columns if c not in (a, b)], "_s.*")


def exact_overlap(a: DataFrame, b: DataFrame, ka: str, kb: str) -> DataFrame:
    """One row: distinct keys of a, b, both, either, a alone."""
    left = a.select(F.col(ka).cast("long").alias("k")).filter("k is not null").distinct().withColumn("in_a", F.lit(1))
    right = b.select(F.col(kb).cast("long").alias("k")).filter("k is not null").distinct().withColumn("in_b", F.lit(1))
    both = left.join(right, "k", "full_outer")
    return both.agg(F.count("in_a").alias("in_a"), F.count("in_b").alias("in_b"), F.sum(F.expr("if(in_a = 1 and in_b = 1, 1, 0)")).alias("in_both"), F.count("*").alias("in_either"), F.sum(F.expr("if(in_b is null, 1, 0)")).alias("only_a"))
