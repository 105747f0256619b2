"""Sketch store: packed sketches in Parquet, by seed and grouping keys."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.seeding import Seed
from ..operators.partial import estimates, merge_by


def write(sketches: DataFrame, path: str, seed: Seed, partition_by: list[str] = (), mode: str = "overwrite") -> None:
    """Partitioned by seed fingerprint, then ``partition_by``; only the partitions in ``sketches`` are replaced."""
    rows = sketches.withColumn("seed_fp", F.lit(seed.fingerprint))
    rows.write.mode(mode).option("partitionOverwriteMode", "dynamic").partitionBy("seed_fp", *partition_by).parquet(path)


def read(spark: SparkSession, path: str, seed: Seed) -> DataFrame:
    """The sketches of this seed alone (a partition filter)."""
    return spark.read.option("basePath", path).parquet(f"{path}/seed_fp={seed.fingerprint}").drop("seed_fp")


def rollup(spark: SparkSession, path: str, seed: Seed, group: list[str] = (), where: str | None = None) -> DataFrame:
    """Estimates for stored sketches merged to ``group``; ``where`` prunes partitions."""
    rows = read(spark, path, seed)
    rows = rows.filter(where) if where else rows
    return estimates(merge_by(rows.select(*group, "sketch"), seed, list(group)), seed)


def merge_into(batch: DataFrame, path: str, seed: Seed, group: list[str], partition_by: list[str] = ()) -> None:
    """Merges new sketches into stored ones: merging again after a replay changes nothing.

    ``partition_by`` are the store's partition columns (among ``group``): only the partitions that the batch
    touches are read and written again. The staged rows of a run have a folder of their own, which goes at its end.
    """
    spark = batch.sparkSession
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{path}/seed_fp={seed.fingerprint}")
    exists = hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(hadoop)
    both = batch.select(*group, "sketch")
    if exists:
        stored = read(spark, path, seed).select(*group, "sketch")
        if partition_by:
            touched = batch.select(*partition_by).distinct()
            stored = stored.join(touched, [stored[c].eqNullSafe(touched[c]) for c in partition_by], "left_semi")
        both = both.unionByName(stored)
    merged = merge_by(both, seed, group)
    staged = f"{path}-staged-{uuid.uuid4().hex}"  # what is being replaced is read no more when it is written
    merged.write.parquet(staged)
    write(spark.read.schema(merged.schema).parquet(staged), path, seed, list(partition_by))
    folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(staged)
    folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(folder, True)
