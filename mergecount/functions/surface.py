"""Entry points for users: estimates in one call, and SQL functions over packed sketches."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import bounds, packed
from ..nested import NestedSeed, derive_nested, nested_seed, route
from ..operators.partial import estimates, sketch_by
from ..operators.setops import overlap
from ..params import derive
from .encode import key64
from .seeding import Seed, init


def distinct_estimate(df: DataFrame, columns: str | list[str], eps: float, delta: float, group: list[str] = (), entropy: int | str = 1, **practical) -> DataFrame:
    """(group..., estimate): distinct values of one or more columns, exact if it can have at most 256, by the single-cut sketch if delta >= 1 / ln n, else by the nested one.

    Sizes are of the practical profile: the accuracy is that measured in the tests, not the proved one.
    """
    names = [columns] if isinstance(columns, str) else list(columns)
    if len(names) == 1 and route(64, delta, {"boolean": 1, "tinyint": 8}.get(dict(df.dtypes)[names[0]])) == "exact":
        return df.groupBy(*group).agg(F.countDistinct(names[0]).cast("double").alias("estimate"))
    key, _ = key64(df, *names)
    keyed = df.select(*group, key.alias("_key64"))
    if route(64, delta) == "single":
        seed = init(derive(64, eps, delta, "practical", **practical), entropy)
        return estimates(sketch_by(keyed, "_key64", seed, group), seed).select(*group, "estimate")
    seed = nested_seed(derive_nested(64, eps, delta, "practical", **practical), entropy)
    return estimates(sketch_by(keyed, "_key64", seed, group), seed).select(*group, "estimate")


def _value(sketch) -> float:
    found = sketch.estimate()
    return found if isinstance(found, float) else found.value


def register(spark: SparkSession, seed: Seed | NestedSeed) -> None:
    """SQL functions sketch_estimate, sketch_merge, sketch_union_agg, sketch_intersection, sketch_difference (of either kind of sketch),
    sketch_info, and table functions sketch_cells (of single sketches), space_report."""
    from ..operators.partial import _empty, _unpack

    @F.pandas_udf("double")
    def sketch_estimate(blobs: pd.Series) -> pd.Series:
        return pd.Series([None if x is None else _value(_unpack(seed, bytes(x))) for x in blobs], dtype="float64")

    def merged(blobs) -> bytes:
        total = None
        for blob in blobs:
            if blob is not None:
                one = _unpack(seed, bytes(blob))
                total = one if total is None else total.merge(one)
        return (total or _empty(seed)).pack()

    @F.pandas_udf("binary")
    def sketch_merge(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([merged(pair) for pair in zip(a, b, strict=True)])

    @F.pandas_udf("binary")
    def sketch_union_agg(blobs: pd.Series) -> bytes:
        return merged(blobs)

    @F.pandas_udf("double")
    def sketch_intersection(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([overlap(seed, bytes(x), bytes(y))[0] for x, y in zip(a, b, strict=True)])

    @F.pandas_udf("double")
    def sketch_difference(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([overlap(seed, bytes(x), bytes(y))[1] for x, y in zip(a, b, strict=True)])

    @F.pandas_udf("codec string, seed_fp long, l int, b int, q int")
    def sketch_info(blobs: pd.Series) -> pd.DataFrame:
        return pd.DataFrame([packed.info(bytes(x)) for x in blobs])[["codec", "seed_fp", "l", "b", "q"]]

    class SketchCells:
        def eval(self, blob: bytes) -> Iterator[tuple[int, int, int]]:
            levels, q, _ = packed.decode(bytes(blob))
            for t, j in zip(*(levels >= 0).nonzero(), strict=True):
                yield int(t), int(j), int(levels[t, j]) + q

    class SpaceReport:
        def eval(self, bits: int, eps: float, delta: float) -> Iterator[tuple[str, bool, float]]:
            for name in bounds.SPACE:
                yield name, bounds.MERGEABLE[name], bounds.space_formula(name, int(bits), float(eps), float(delta))

    for name, f in (("sketch_estimate", sketch_estimate), ("sketch_merge", sketch_merge), ("sketch_union_agg", sketch_union_agg), ("sketch_intersection", sketch_intersection), ("sketch_difference", sketch_difference), ("sketch_info", sketch_info)):
        spark.udf.register(name, f)
    spark.udtf.register("sketch_cells", F.udtf(SketchCells, returnType="tab int, bin int, level int"))
    spark.udtf.register("space_report", F.udtf(SpaceReport, returnType="algorithm string, mergeable boolean, formula double"))
