"""Levels and bins as Spark expressions: XOR of table entries, one for each four bits of the key.

A pairwise map over GF(2^64) is affine over GF(2), so 16 lookups in 16 x 16 words give its value.
All tables of a sketch share one literal array per map, and the table number only shifts the index,
so the expression has one size for any number of tables and stays inside generated code. Bins are
pairwise here (k = 2): good for parity with SQL and for wide keys, not for accuracy claims on dense
integer keys.
"""

from __future__ import annotations

import json
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .families import PolyHash
from .seeding import draw


@dataclass(frozen=True)
class NativeSeed:
    """Coefficients of l pairwise level and bin maps over GF(2^64)."""

    l: int  # noqa: E741
    b: int
    entropy: int | str

    def _tables(self, what: str) -> list[int]:
        out: list[int] = []
        for t in range(self.l):
            number = draw(self.entropy, 128, f"native-{what}-{t}")
            words = PolyHash([number & (2**64 - 1), number >> 64], 64).nibbles().ravel()
            out += [int(w) - (1 << 64) if int(w) >> 63 else int(w) for w in words]
        return out

    def level_words(self) -> list[int]:
        return self._tables("level")

    def bin_words(self) -> list[int]:
        return self._tables("bin")


def _literal(words: list[int]) -> Column:
    return F.from_json(F.lit(json.dumps(words)), F.lit("array<bigint>"))  # folded to one literal by the optimizer


def affine64(key: Column, words: list[int], table: Column) -> Column:
    data = _literal(words)
    out = None
    for place in range(16):
        digit = F.shiftrightunsigned(key, 4 * place).bitwiseAND(F.lit(15))
        word = F.get(data, (table * 256 + 16 * place + digit).cast("int"))
        out = word if out is None else out.bitwiseXOR(word)
    return out


def trailing_zeros(y: Column) -> Column:
    """Trailing zeros of a 64-bit word; 64 for zero. The least long has no predecessor under ANSI rules; it has 63.

    ``y`` stands here twice only: the optimizer may write the expression out where a filter needs it.
    """
    return F.coalesce(F.bit_count(F.bitwise_not(y).bitwiseAND(F.try_subtract(y, F.lit(1).cast("long")))), F.lit(63)).cast("int")


def levels_and_bins(df: DataFrame, key: str, seed: NativeSeed, keep: list[str]) -> DataFrame:
    """(keep..., tab, bin, level): one row per row and table; null keys are left out."""
    rows = df.filter(F.col(key).isNotNull()).select(*keep, F.col(key).cast("long").alias("_k"), F.explode(F.sequence(F.lit(0), F.lit(seed.l - 1))).alias("tab"))
    words = rows.select(*keep, "tab", affine64(F.col("_k"), seed.level_words(), F.col("tab")).alias("_f"), affine64(F.col("_k"), seed.bin_words(), F.col("tab")).alias("_h"))
    return words.select(*keep, "tab", F.col("_h").bitwiseAND(F.lit(seed.b - 1)).cast("int").alias("bin"), trailing_zeros(F.col("_f")).alias("level"))


def ideal_levels_and_bins(df: DataFrame, key: str, tables: int, bins: int, keep: list[str]) -> DataFrame:
    """The same rows from xxHash with a seed per table: the stand-in for fully random functions (a random-oracle assumption)."""
    rows = df.filter(F.col(key).isNotNull()).select(*keep, F.col(key).cast("long").alias("_k"), F.explode(F.sequence(F.lit(0), F.lit(tables - 1))).alias("tab"))
    word = lambda what: F.xxhash64(F.lit(what), "tab", "_k")
    return rows.select(*keep, "tab", word("bin").bitwiseAND(F.lit(bins - 1)).cast("int").alias("bin"), trailing_zeros(word("level")).alias("level"))
