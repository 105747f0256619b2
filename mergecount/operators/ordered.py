"""Joins by order: as-of (the last row before) and interval (rows within a range)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W


def asof_join(left: DataFrame, right: DataFrame, by: list[str], time: str, slice_of: Column, values: list[str]) -> DataFrame:
    """``left`` with ``values`` of the last row of ``right`` with the same ``by`` at or before its ``time`` (null if there is none).

    Rows are dealt by (by, slice), ``slice_of`` being a column of ``time`` that never falls with it (a day, say), so a
    hot key is many tasks' work. The last row of each slice goes on to the later slices as one slim row.
    Of right rows at one time the one with the largest values counts. Null times take no part on the right.
    """
    both = [*by, time]
    payload = F.struct(*[F.col(c) for c in values])
    rows = right.filter(F.col(time).isNotNull()).select(*both, slice_of.alias("_slice"), payload.alias("_value"), F.lit(None).cast(left.select(F.struct("*")).schema[0].dataType).alias("_row"))
    asks = left.select(*both, slice_of.alias("_slice"), F.lit(None).cast(rows.schema["_value"].dataType).alias("_value"), F.struct("*").alias("_row"))
    lasts = rows.groupBy(*by, "_slice").agg(F.max(F.struct(time, "_value")).alias("_last"))
    needed = asks.groupBy(*by, "_slice").agg(F.lit(None).cast(lasts.schema["_last"].dataType).alias("_last"))
    before = W.partitionBy(*by).orderBy("_slice").rowsBetween(W.unboundedPreceding, -1)
    merged = lasts.unionByName(needed).groupBy(*by, "_slice").agg(F.max("_last").alias("_last"))
    carried = merged.withColumn("_before", F.last("_last", ignorenulls=True).over(before)).filter("_before is not null")
    first = carried.select(*by, F.lit(None).cast(left.schema[time].dataType).alias(time), "_slice", F.col("_before._value").alias("_value"), F.lit(None).cast(asks.schema["_row"].dataType).alias("_row"))
    turn = F.when(F.col("_row").isNull(), 0).otherwise(1)
    inside = W.partitionBy(*by, "_slice").orderBy(F.col(time).asc_nulls_first(), turn, "_value").rowsBetween(W.unboundedPreceding, W.currentRow)
    found = rows.unionByName(asks).unionByName(first).withColumn("_found", F.last("_value", ignorenulls=True).over(inside))
    return found.filter("_row is not null").select("_row.*", *[F.when(F.col(time).isNotNull(), F.col(f"_found.{c}")).alias(f"asof_{c}") for c in values])


def interval_join(points: DataFrame, ranges: DataFrame, at: str, begin: str, end: str, width: int) -> DataFrame:
    """Pairs with begin <= at < end (whole numbers): both sides meet in bins of ``width``, so the join is on equal bins.

    A range is repeated once for each bin that it touches; choose a width near the usual range's length.
    """
    floor = lambda c: F.floor(c / width)
    wide = ranges.filter(F.col(end) > F.col(begin)).withColumn("_bin", F.explode(F.sequence(floor(F.col(begin)), floor(F.col(end) - 1))))
    return points.withColumn("_bin", floor(F.col(at))).join(wide, "_bin").filter((F.col(at) >= F.col(begin)) & (F.col(at) < F.col(end))).drop("_bin")
