"""Keys of the universe from columns of any type.

``lossless`` says whether different values always get different keys. Digests do not promise that
and bring back the assumption of an ideal hash, which the sketches themselves avoid.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


def key64(df: DataFrame, *columns: str) -> tuple[Column, bool]:
    """64-bit key of one or more columns, null if any is null, and whether it is lossless."""
    kinds = [df.schema[c].dataType for c in columns]
    null = None
    for c in columns:
        null = F.col(c).isNull() if null is None else null | F.col(c).isNull()
    if len(columns) == 1:
        value, lossless = _one(F.col(columns[0]), kinds[0])
        return F.when(null, F.lit(None).cast("long")).otherwise(value), lossless
    if len(columns) == 2 and all(isinstance(k, (T.ByteType, T.ShortType, T.IntegerType)) for k in kinds):
        high, low = (F.col(c).cast("long") for c in columns)
        return F.when(~null, F.shiftleft(high, 32).bitwiseOR(low.bitwiseAND(F.lit(0xFFFFFFFF)))), True
    parts = [_canonical(F.col(c), k) for c, k in zip(columns, kinds, strict=True)]
    return F.when(~null, F.xxhash64(*parts)), False


def _one(col: Column, kind: T.DataType) -> tuple[Column, bool]:
    if isinstance(kind, (T.BooleanType, T.ByteType, T.ShortType, T.IntegerType, T.LongType)):
        return col.cast("long"), True
    if isinstance(kind, T.DateType):
        return F.unix_date(col).cast("long"), True
    if isinstance(kind, T.TimestampType):
        return F.unix_micros(col), True
    if isinstance(kind, T.TimestampNTZType):
        # microseconds of the wall clock, whatever time zone the session has
        return (F.unix_date(col.cast("date")).cast("long") * 86_400_000_000 + _clock_micros(col)), True
    if isinstance(kind, T.DecimalType) and kind.precision <= 18:
        return (col * F.lit(10**kind.scale).cast("decimal(19,0)")).cast("long"), True
    if isinstance(kind, (T.FloatType, T.DoubleType)):
        return F.xxhash64(_canonical(col, kind)), False
    return F.xxhash64(_canonical(col, kind)), False


def _clock_micros(col: Column) -> Column:
    return F.hour(col).cast("long") * 3_600_000_000 + F.minute(col).cast("long") * 60_000_000 + (F.date_part(F.lit("SECOND"), col) * 1_000_000).cast("long")


def _canonical(col: Column, kind: T.DataType) -> Column:
    """One form for equal values: 0.0 for -0.0, one NaN, maps as sorted entries."""
    if isinstance(kind, (T.FloatType, T.DoubleType)):
        return F.when(F.isnan(col), F.lit(float("nan"))).when(col == 0, F.lit(0.0)).otherwise(col.cast("double"))
    if isinstance(kind, T.ArrayType):
        return F.transform(col, lambda x: _canonical(x, kind.elementType))
    if isinstance(kind, T.MapType):
        return F.to_json(F.array_sort(F.map_entries(col)))
    if isinstance(kind, T.StructType):
        return F.struct(*[_canonical(col[f.name], f.dataType).alias(f.name) for f in kind.fields])
    return col


def key256(df: DataFrame, *columns: str) -> Column:
    """256-bit digest (binary) of the columns in canonical form."""
    parts = [_canonical(F.col(c), df.schema[c].dataType).cast("string") for c in columns]
    sized = [F.coalesce(F.concat(F.length(p).cast("string"), F.lit(":"), p), F.lit("-")) for p in parts]  # lengths keep neighbours apart
    return F.unhex(F.sha2(F.concat(*sized).cast("binary"), 256))
