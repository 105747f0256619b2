"""Helpers shared by the training-data operators: tables, shared storage, prefix sums."""

from __future__ import annotations

import atexit
import gc
import json
import math
import shutil
import tempfile
import uuid
from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

#: Keys that are broadcast as hot ones at most, and buckets of a stored table (the limit that Spark sets).
HOT, MOST_BUCKETS = 10_000, 100_000

#: Bytes of a stored row group: what a writing task holds.
ROW_GROUP = 16 << 20

#: ASCII whitespace is what separates words in every contract of this package.
WORD = "[^\\x20\\x09-\\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given Parquet tables, read by Spark only (any file system)."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share (spark.checkpoint.dir); a temporary one only where it is unset."""
    sc = spark.sparkContext
    path = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir")
    if path:
        return path
    jvm_dir = sc._jsc.sc().getCheckpointDir()
    if jvm_dir.isDefined():
        return jvm_dir.get()
    own = tempfile.mkdtemp(prefix="mergecount-")
    atexit.register(shutil.rmtree, own, True)
    sc.setCheckpointDir(own)
    return own


def run_dir(spark: SparkSession) -> str:
    """This application's own folder in the shared one."""
    return f"{shared_dir(spark)}/mergecount-llm/{spark.sparkContext.applicationId}"


def materialize(df: DataFrame, name: str, codec: str = "zstd") -> DataFrame:
    """Write to the shared folder and read back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = f"{run_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", codec).option("parquet.block.size", ROW_GROUP).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def release(spark: SparkSession) -> None:
    """Lets go of what finished steps left with the driver: its shuffles, broadcasts and the heap that they took.

    Spark drops the first two when the driver's garbage is collected, which a heap that may still grow puts off.
    """
    gc.collect()  # handles in Python keep plans in the JVM
    spark.sparkContext._jvm.System.gc()


def once(value: Column, use: Callable[[Column], Column]) -> Column:
    """``use`` of a value that is computed once: a lambda's variable, however often ``use`` names it."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def hash60(*cols: Column) -> Column:
    """Uniform 60-bit order from MD5, the same in any SQL engine; null columns are left out."""
    text = F.concat_ws(":", *[c.cast("string") for c in cols])
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 15), 16, 10).cast("long")


def bucket_count(rows: int) -> int:
    """Buckets for a prefix sum: about 64 rows each on small tables, 65,536 at most."""
    return 1 << max(0, math.ceil(math.log2(max(1, min(max(1, rows // 64), max(4096, rows >> 16), 1 << 16)))))


def prefix_sums(df: DataFrame, group: list[str], bucket: str, order: list[Column], sums: dict[str, Column], carry: DataFrame | None = None) -> DataFrame:
    """Exclusive running sums within each group, without gathering a group in one task.

    ``bucket`` is a long column whose order agrees with ``order`` and which spreads every group
    over many values (65,536 at most, see ``bucket_count``). Totals of each group and bucket are summed
    in bucket order; each such base then travels as one more row of its bucket and comes first in it,
    so rows meet their base by the deal itself: one shuffle of ``df``, one plan at any size, no lookup
    join. Rows are dealt by bucket alone, so a group that holds a third of all rows is as evenly spread
    as any other. ``carry``: columns of each group (group..., others) that its rows get in the same way.
    ``df`` is read twice: materialize it.
    """
    names, kinds = list(sums), dict(df.dtypes)
    cells = df.groupBy(*group, bucket).agg(*[F.sum(sums[n]).alias(n) for n in names])
    before = W.partitionBy(*group).orderBy(bucket).rowsBetween(W.unboundedPreceding, -1)
    bases = cells.select(*group, bucket, *[F.coalesce(F.sum(n).over(before), F.lit(0)).cast("long").alias(n) for n in names])
    carried = []
    if carry is not None:
        carried = [c for c in carry.columns if c not in group]
        bases = bases.alias("b").join(carry.alias("c"), [F.col(f"b.{g}").eqNullSafe(F.col(f"c.{g}")) for g in group])
        bases = bases.select(*[F.col(f"b.{c}") for c in [*group, bucket, *names]], *[F.col(f"c.{c}") for c in carried])
        kinds |= dict(carry.dtypes)
    own = [c for c in df.columns if c not in group and c != bucket]
    rows = df.select(*group, bucket, F.lit(1).alias("_turn"), *own, *[sums[n].cast("long").alias(n) for n in names], *[F.lit(None).cast(kinds[c]).alias(c) for c in carried])
    first = bases.select(*group, bucket, F.lit(0).alias("_turn"), *[F.lit(None).cast(kinds[c]).alias(c) for c in own], *names, *carried)
    inside = W.partitionBy(bucket, *group).orderBy("_turn", *order).rowsBetween(W.unboundedPreceding, -1)
    dealt = rows.union(first).repartition(F.col(bucket))
    found = dealt.select(*group, bucket, "_turn", *own, *[F.sum(n).over(inside).alias(n) for n in names], *[F.first(c).over(inside).alias(c) for c in carried])
    return found.filter("_turn = 1").select(*df.columns, *names, *carried)


def join_hot(rows: DataFrame, lookup: DataFrame, on: str, total: int, count: str = "_n", floor: int = 64) -> DataFrame:
    """``rows`` joined with the one row that ``lookup`` has for each value of ``on``; ``count`` in it says how many rows have that value.

    Values with over total / HOT rows are HOT at most (so the driver may know them): their lookup rows are
    broadcast and their rows stay where they are. All other values are joined by Spark's choice, and none of
    them is a large part of ``rows``. Where there are hot values ``rows`` is read twice: materialize it.
    """
    limit = max(floor, total // HOT)
    lookup = materialize(lookup, "lookup")
    hot = [r[0] for r in lookup.filter(F.col(count) > limit).select(on).collect()]
    if not hot:
        return rows.join(lookup, on)
    among = F.col(on).isin(hot)
    many = rows.filter(among).join(F.broadcast(lookup.filter(F.col(count) > limit)), on)
    return many.unionByName(rows.filter(~among).join(lookup.filter(F.col(count) <= limit), on))


def _murmur3(values: np.ndarray) -> np.ndarray:
    """Spark's hash of int values (public algorithm, seed 42), as signed 32-bit numbers."""
    turn = lambda x, r: x << np.uint32(r) | x >> np.uint32(32 - r)
    k = turn(values.astype(np.uint32) * np.uint32(0xCC9E2D51), 15) * np.uint32(0x1B873593)
    h = turn(np.uint32(42) ^ k, 13) * np.uint32(5) + np.uint32(0xE6546B64) ^ np.uint32(4)
    h = (h ^ h >> np.uint32(16)) * np.uint32(0x85EBCA6B)
    h = (h ^ h >> np.uint32(13)) * np.uint32(0xC2B2AE35)
    return (h ^ h >> np.uint32(16)).view(np.int32)


def slot_values(n: int) -> list[int]:
    """For every bucket 0..n-1 an int that Spark's bucketing puts there."""
    found, at = np.full(n, -1, dtype=np.int64), 0
    while (found < 0).any():
        values = np.arange(at, at + 4 * n, dtype=np.int64)
        where = _murmur3(values.astype(np.uint32)).astype(np.int64) % n
        found[where[::-1]] = np.where(found[where[::-1]] < 0, values[::-1], found[where[::-1]])
        at += 4 * n
    return found.tolist()


def stored_by_task(df: DataFrame, name: str) -> tuple[DataFrame, int]:
    """Writes ``df`` as a table with a bucket for every task, where the rows lie: nothing moves. The table and the number of buckets.

    Adds _slot (int, the task) and _row (its rows, from 0). Rows for ``beside`` are made from these two.
    """
    spark = df.sparkSession
    n = df._jdf.queryExecution().toRdd().getNumPartitions()
    if n > MOST_BUCKETS:
        df, n = df.coalesce(MOST_BUCKETS), MOST_BUCKETS
    n = max(1, n)
    slots = F.from_json(F.lit(json.dumps(slot_values(n))), F.lit("array<int>"))  # folded to one literal
    rows = df.select("*", F.get(slots, F.spark_partition_id()).alias("_slot"), F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1)).alias("_row"))
    table, path = f"mergecount_{uuid.uuid4().hex}", f"{run_dir(spark)}/{name}-{uuid.uuid4().hex}"
    writers = "spark.sql.maxConcurrentOutputFileWriters"  # a task has one bucket: with this no sort comes before the write
    was = spark.conf.get(writers)
    spark.conf.set(writers, "4")
    try:
        rows.write.option("path", path).option("compression", "zstd").option("parquet.block.size", ROW_GROUP).bucketBy(n, "_slot").saveAsTable(table)
    finally:
        spark.conf.set(writers, was)
    stored = spark.table(table)
    stored.schema  # resolved: the plan keeps the files and their buckets, the catalog entry can go  # noqa: B018
    spark.sql(f"drop table {table}")
    return stored, n


def beside(stored: DataFrame, slots: int, side: DataFrame) -> DataFrame:
    """``stored`` (from ``stored_by_task``) with the columns of ``side`` (one row for each _slot, null where there is none).

    Only ``side`` is moved, to where its slot's files are read (it is dealt as the buckets are, else Spark
    might deal the stored rows anew); the stored rows are neither shuffled nor sorted.
    """
    return stored.join(side.repartition(slots, "_slot").hint("shuffle_hash"), "_slot", "left")


def numbered(df: DataFrame, name: str, number: str = "_row") -> DataFrame:
    """``df`` in the shared folder with a number for every row, unique whatever its columns hold."""
    return materialize(df.withColumn(number, F.monotonically_increasing_id()), name, "snappy")


def cleanup(spark: SparkSession) -> None:
    """Deletes all that this application has left in the shared folder (other runs' tables stay); call it when no result is read any more."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(run_dir(spark))
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
