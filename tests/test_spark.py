import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from mergecount import workloads
from mergecount.functions import encode, native, seeding, surface
from mergecount.functions.families import PolyHash
from mergecount.operators import cells, partial, setops
from mergecount.params import SketchParams
from mergecount.plans.planner import choose
from mergecount.sketch import Context, Sketch
from mergecount.sources import store

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
P = SketchParams(3, 64, 6)
SEED = seeding.init(P, "spark")


def plain(df):
    norm = lambda v: None if v is None or str(v) in ("nan", "<NA>", "NaT") else round(v, 6) if isinstance(v, float) else v
    cols = sorted(df.columns)
    return cols, sorted(str([norm(v) for v in r]) for r in df[cols].astype(object).itertuples(index=False, name=None))


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from read_parquet('{sf}/{t}.parquet')")
    return con


#: One query per plan shape; the driver runs all of them.
SAMPLE = ["raw_cells", "required_cut", "main_estimate_pairwise", "nested_estimate_pairwise", "cube_by_merge", "binned_levels_baseline", "adversarial_split", "window_distinct_pairwise", "kwise_within"]


@pytest.mark.parametrize("name", SAMPLE)
def test_query_equals_sql(spark, sf, duck, name):
    if name == "kwise_within":
        got = workloads.queries()[name](spark, sf).toPandas()
        assert got["within"].all()
        return
    assert plain(workloads.queries()[name](spark, sf).toPandas()) == plain(duck.sql(workloads.oracle_sql()[name]).df())


def test_every_oracle_has_a_query():
    assert set(workloads.oracle_sql()) <= set(workloads.queries())


def test_native_levels_on_extreme_keys(spark):
    keys = [0, 1, -1, 2**63 - 1, -(2**63), 12345, None]
    seed = native.NativeSeed(3, 64, "extreme")
    df = spark.createDataFrame([(k,) for k in keys], "k long")
    got = {(r["k"], r["tab"]): (r["bin"], r["level"]) for r in native.levels_and_bins(df.withColumn("kk", F.col("k")), "kk", seed, ["k"]).collect()}
    assert len(got) == 3 * 6
    for t in range(3):
        level, bins = (seeding.draw("extreme", 128, f"native-{w}-{t}") for w in ("level", "bin"))
        f, h = (PolyHash([n & (2**64 - 1), n >> 64], 64) for n in (level, bins))
        for k in keys[:-1]:
            y = f(k % 2**64)
            expected = 64 if y == 0 else (y & -y).bit_length() - 1
            assert got[k, t] == (h(k % 2**64) & 63, expected)


def test_packed_equals_memory_for_any_partitioning(spark):
    df = spark.range(2000).select((F.col("id") % 700).alias("k"), (F.col("id") % 3).cast("string").alias("g"))
    expected = {g: Sketch(Context.of(SEED)).update(np.array([i % 700 for i in range(2000) if str(i % 3) == g], dtype=np.uint64)).pack() for g in "012"}
    for parts in (1, 5):
        got = {r["g"]: bytes(r["sketch"]) for r in partial.sketch_by(df.repartition(parts), "k", SEED, ["g"]).collect()}
        assert got == expected


def test_empty_and_null_keys(spark):
    df = spark.createDataFrame([(None,)], "k long")
    assert partial.sketch_by(df, "k", SEED).count() == 0
    assert cells.raw_cells(df, "k", native.NativeSeed(2, 16, 1)).count() == 0


def test_encoders(spark):
    df = spark.sql("select double(0.0) a, double(-0.0) b, 'x' s, date'2020-01-01' d, 1 i, 2 j, decimal(1.25) m, map('a', 1, 'b', 2) m1, map('b', 2, 'a', 1) m2")
    k = lambda *c: encode.key64(df, *c)
    row = df.select(k("a")[0].alias("a"), k("b")[0].alias("b"), k("i", "j")[0].alias("ij"), k("d")[0].alias("d"), k("m1")[0].alias("m1"), k("m2")[0].alias("m2"), encode.key256(df, "s").alias("h")).first()
    assert row["a"] == row["b"] and row["ij"] == (1 << 32) + 2 and row["d"] == 18262 and row["m1"] == row["m2"] and len(row["h"]) == 32
    assert k("i")[1] and not k("s")[1]


def test_store_round_trip(spark, tmp_path):
    path = f"file://{tmp_path}/store"
    df = spark.range(500).select("id", (F.col("id") % 2).alias("day"))
    store.write(partial.sketch_by(df, "id", SEED, ["day"]), path, SEED, ["day"])
    whole = store.rollup(spark, path, SEED).first()
    assert abs(whole["estimate"] - 500) < 250
    store.merge_into(partial.sketch_by(df, "id", SEED, ["day"]), path, SEED, ["day"])
    assert store.rollup(spark, path, SEED).first()["estimate"] == whole["estimate"]


def test_sql_functions(spark):
    surface.register(spark, SEED)
    partial.sketch_by(spark.range(300).withColumn("g", F.col("id") % 2), "id", SEED, ["g"]).createOrReplaceTempView("sk")
    one = spark.sql("select sketch_estimate(sketch) e, sketch_info(sketch).b b from sk").collect()
    both = spark.sql("select sketch_estimate(u) e from (select sketch_union_agg(sketch) u from sk)").first()["e"]
    assert len(one) == 2 and one[0]["b"] == 64 and both > one[0]["e"]
    assert spark.sql("select count(*) n from sk, lateral sketch_cells(sketch)").first()["n"] > 0
    assert spark.sql("select * from space_report(64, 0.1, 0.01)").count() == 7
    est = surface.distinct_estimate(spark.range(1000), "id", 0.2, 0.1, b=256, l=5, k=8).first()["estimate"]
    assert abs(est - 1000) < 300


def test_set_operations(spark):
    c = Context.of(seeding.init(SketchParams(9, 1024, 8), 9))
    a, b = (Sketch(c).update(np.arange(*r, dtype=np.uint64)) for r in ((0, 400), (200, 600)))
    assert abs(setops.union_estimate(a, b) - 600) < 90
    assert abs(setops.intersection_estimate(a, b)[0] - 200) < 120 and abs(setops.difference_estimate(a, b)[0] - 200) < 120


def test_partial_aggregation_and_pruning_in_the_plan(spark, sf):
    plan = workloads.raw_cells(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "partial_max" in plan and plan.count("Exchange hashpartitioning") == 1
    assert "l_returnflag" in plan and "l_extendedprice" not in plan


def test_form_choice():
    assert choose(P, 100_000, 1).form == "packed" and choose(SketchParams(9, 1024, 8), 1000, 10_000, rows=20_000).form == "cells"
