"""Helpers for hot keys: equal to plain joins and sums, whatever the limits, and without moving what they promise to leave."""

import os
import re

import pytest
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from mergecount.llm import common as C
from mergecount.llm import simhash, warc
from mergecount.llm.components import connected_components


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_slots_are_sparks_buckets(spark):
    for n in (1, 2, 7, 64, 1000):
        rows = spark.createDataFrame([(int(v),) for v in C.slot_values(n)], "v int")
        assert [r[0] for r in rows.select(F.pmod(F.hash("v"), F.lit(n))).collect()] == list(range(n))


@pytest.mark.parametrize("hot", [0, 3, 10_000])
def test_join_hot_equals_a_join(spark, monkeypatch, hot):
    """No key, some keys or all keys may count as hot."""
    monkeypatch.setattr(C, "HOT", max(1, hot))
    rows = C.materialize(spark.range(6000).select(F.when(F.col("id") % 3 == 0, 1).otherwise(F.col("id") % 50).alias("k"), "id"), "t-rows")
    lookup = rows.groupBy("k").agg(F.count("*").alias("_n"), F.max("id").alias("m"))
    got = C.join_hot(rows, lookup, "k", 6000, floor=1 if hot else 10**9)
    assert sorted(map(tuple, got.select("k", "id", "m").collect())) == sorted(map(tuple, rows.join(lookup, "k").select("k", "id", "m").collect()))


def test_prefix_sums_equal_a_window(spark):
    rows = spark.range(5000).select("id", F.when(F.col("id") % 3 == 0, None).otherwise(F.col("id") % 7).alias("g"), (F.col("id") % 11).alias("n"), C.hash60(F.lit("s"), F.col("id")).alias("h"))
    rows = C.materialize(rows.withColumn("b", F.shiftright("h", 54)), "t-prefix")
    carry = rows.groupBy("g").agg(F.sum("n").alias("all"))
    got = C.prefix_sums(rows, ["g"], "b", [F.col("h")], {"before": F.col("n")}, carry)
    window = W.partitionBy("g").orderBy("h")
    plain = rows.withColumn("before", F.coalesce(F.sum("n").over(window.rowsBetween(W.unboundedPreceding, -1)), F.lit(0))).withColumn("all", F.sum("n").over(W.partitionBy("g")))
    assert sorted(map(str, got.select("id", "before", "all").collect())) == sorted(map(str, plain.select("id", "before", "all").collect()))
    assert "BroadcastHashJoin" not in re.sub(r"(?s).*Window", "", plan_of(got)) and got.count() == 5000


def test_stored_rows_stay_where_they_are(spark):
    rows = spark.range(0, 3000, 1, 5).select("id", F.md5(F.col("id").cast("string")).alias("text"))
    stored, slots = C.stored_by_task(rows, "t-stored")
    told = stored.groupBy("_slot").agg(F.sort_array(F.collect_list(F.struct("_row", "id"))).alias("all")).select("_slot", F.col("all.id").alias("ids"))
    # a side that has been through another shuffle, as all real ones have
    told = told.repartition(17, "ids")
    joined = C.beside(stored, slots, told).withColumn("same", F.get("ids", F.col("_row").cast("int")) == F.col("id"))
    assert slots == 5 and joined.filter("same").count() == 3000
    side = plan_of(joined).split("ShuffledHashJoin")[1].split("Exchange")[0]
    assert "Bucketed: true" in side  # the stored side is read in place: no exchange above its scan


def test_payloads_are_not_shuffled(spark, sf, monkeypatch):
    plans = []
    keep = C.materialize
    monkeypatch.setattr(warc.C, "materialize", lambda df, name, *a: plans.append((name, plan_of(df))) or keep(df, name, *a))
    warc.write_archives(spark.read.parquet(f"{sf}/pages.parquet"))
    last = dict(plans)["warc"]
    assert "payload" not in "".join(re.findall(r"Exchange.*", last))


def test_hot_anchors_are_cut_before_the_shuffle(spark):
    """Many fingerprints within two bits of one anchor: the same groups with and without the early cut."""
    fps = C.materialize(spark.range(3000).select((F.lit(5) + F.shiftleft(F.col("id") * 3, 33)).cast("long").alias("fp")), "t-fps")
    hot = simhash.hot_anchors(fps, 34 * 3000, floor=100)
    assert hot.count() > 0 and hot.agg(F.max("n")).first()[0] == 3000
    early, late = (connected_components(simhash.links(fps, floor), "a", "b") for floor in (100, 10**9))
    assert sorted(map(tuple, early.distinct().collect())) == sorted(map(tuple, late.distinct().collect()))


def test_components_of_a_star_and_a_path(spark, monkeypatch):
    monkeypatch.setattr(C, "HOT", 20)
    links = spark.range(1, 4000).select(F.lit(0).cast("long").alias("a"), F.col("id").alias("b")).union(spark.range(5000, 5300).select(F.col("id"), F.col("id") + 1))
    got = connected_components(links, "a", "b").distinct()
    assert sorted(map(tuple, got.groupBy("root").count().collect())) == [(0, 4000), (5000, 301)]


def test_cleanup_leaves_other_runs(spark):
    folder = C.shared_dir(spark)
    other = f"{folder.removeprefix('file:')}/mergecount-llm/another-run"
    os.makedirs(other, exist_ok=True)
    C.materialize(spark.range(3).toDF("x"), "t-clean").count()
    assert os.path.isdir(C.run_dir(spark).removeprefix("file:"))
    C.cleanup(spark)
    assert os.path.isdir(other) and not os.path.exists(C.run_dir(spark).removeprefix("file:"))


def test_rounds_leave_no_garbage_with_the_driver(spark, monkeypatch):
    """What finished steps left (here a broadcast table that nothing names any more) goes with the next round, not when the heap is full."""
    runtime, release, left = spark.sparkContext._jvm.java.lang.Runtime.getRuntime(), C.release, []

    def measured(session):
        release(session)
        left.append((runtime.totalMemory() - runtime.freeMemory()) >> 20)

    monkeypatch.setattr(C, "release", measured)
    wide = spark.range(400_000).select("id", F.repeat(F.lit("x"), 100).alias("x"))
    assert spark.range(10).join(F.broadcast(wide), "id").count() == 10
    del wide
    links = spark.createDataFrame([(i, i + 1) for i in range(12)], "a long, b long")
    assert connected_components(links, "a", "b").filter("root = 0").count() == 13
    assert len(left) > 1 and left[-1] < left[0] + 30, left  # MB after each round
