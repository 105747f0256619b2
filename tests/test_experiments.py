"""Experiments and joins by order: against their SQL and by hand."""

import random

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from mergecount import experiments, packed, workloads
from mergecount.functions import seeding
from mergecount.operators import ordered
from mergecount.params import SketchParams
from mergecount.sketch import Context, Sketch, four_times_bins, rho_inv_table

TABLES = ("customer", "orders", "lineitem", "events", "part", "documents", "pages", "conversations")
#: Those that take long or draw at random on tiny tables are left to the larger runs.
FAST = ("cardinality_sweep", "column_space", "operation_counts", "level_tails", "event_frequencies", "cut_forms_agree", "estimate_at_any_cut", "cut_sharing_ablation", "communication_measured", "seed_report", "form_choice",
        "tail_bounds_more", "inverse_tables", "cost_drops", "balls_thrown", "asof_purchase_view", "distinct_in_ranges", "nested_store_within", "sketch_store_within", "packed_cube_within", "stored_sets_within", "walk_tail", "deviation_walk",
        "packed_stream_within", "session_stream", "dedup_stream_exact")


@pytest.fixture(scope="module")
def sql(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from read_parquet('{sf}/{t}.parquet')")
    return con, workloads.oracle_sql()


def plain(df):
    norm = lambda v: None if v is None or str(v) in ("nan", "<NA>", "NaT") else round(float(v), 6) if isinstance(v, (int, float, np.number)) and not isinstance(v, bool) else str(v)
    cols = sorted(df.columns)
    return cols, sorted(str([norm(v) for v in r]) for r in df[cols].astype(object).itertuples(index=False, name=None))


@pytest.mark.parametrize("name", FAST)
def test_equals_sql(spark, sf, sql, name):
    con, oracles = sql
    assert plain(workloads.queries()[name](spark, sf).toPandas()) == plain(con.sql(oracles[name]).df())


def test_asof_join_with_ties_nulls_and_a_hot_key(spark):
    rng = random.Random(1)
    left = [(rng.choice([1, 1, 1, 2, None]), rng.choice([None, *range(40)]), i) for i in range(120)]
    right = [(rng.choice([1, 1, 2, 3, None]), rng.choice([None, *range(40)]), rng.randrange(9)) for _ in range(90)]
    a = spark.createDataFrame(left, "k int, t int, i int")
    b = spark.createDataFrame(right, "k int, t int, v int")
    got = {r["i"]: r["asof_v"] for r in ordered.asof_join(a, b, ["k"], "t", F.floor(F.col("t") / 8), ["v"]).collect()}
    assert len(got) == len(left)
    for k, t, i in left:
        before = [(x, v) for key, x, v in right if key == k and x is not None and t is not None and x <= t]
        assert got[i] == (max(before)[1] if before else None), (k, t, i)


def test_interval_join(spark):
    rng = random.Random(2)
    points, ranges = [(rng.randrange(-50, 300),) for _ in range(200)], [(i, a := rng.randrange(-50, 250), a + rng.randrange(-2, 90)) for i in range(40)]
    got = ordered.interval_join(spark.createDataFrame(points, "p int"), spark.createDataFrame(ranges, "i int, lo int, hi int"), "p", "lo", "hi", 16).select("p", "i").collect()
    assert sorted(map(tuple, got)) == sorted((p, i) for (p,) in points for i, lo, hi in ranges if lo <= p < hi)


def test_cells_of_an_indexed_sketch():
    context = Context.of(seeding.init(SketchParams(3, 256, 6), "indexed"))
    sketch = Sketch(context).update(np.arange(700, dtype=np.uint64) * np.uint64(experiments.ODD))
    blob = sketch.pack("indexed")
    assert (packed.decode(blob)[0] == sketch.levels).all()
    assert all(packed.cell(blob, t, j) == sketch.levels[t, j] for t in range(3) for j in range(256))
    with pytest.raises(ValueError):
        packed.cell(sketch.pack(), 0, 0)


def test_rounded_inverse():
    p = four_times_bins(SketchParams(5, 256, 8))
    assert p.b == 1024 and p.k == 68
    sketch = Sketch(Context.of(seeding.init(p, "inverse"))).update(np.arange(3000, dtype=np.uint64))
    exact, rounded = sketch.estimate().value, sketch.estimate(inverse=rho_inv_table(1024, 0.01)).value
    assert 0 < abs(rounded / exact - 1) <= 0.0101


def test_small_types_are_counted_exactly(spark):
    from mergecount.functions.surface import distinct_estimate

    rows = spark.range(1000).select((F.col("id") % 37).cast("byte").alias("x"))
    assert distinct_estimate(rows, "x", 0.1, 0.01).first()["estimate"] == 37.0


def test_sessions_end_at_gaps(spark):
    from mergecount.functions.native import NativeSeed
    from mergecount.operators import cells
    from mergecount.streaming.windows import session_cells

    seed = NativeSeed(2, 64, "s")
    rows = spark.createDataFrame([(1, 0, 5), (1, 50, 6), (1, 50, 5), (1, 200, 7), (2, 10, 5)], "g int, t int, k long").withColumn("at", F.timestamp_seconds("t"))
    got = session_cells(rows, "at", "k", seed, "100 seconds", ["g"]).select("g", F.col("window.start").cast("long").alias("s"), "tab", "bin", "level").collect()
    expected = []
    for g, s, keys in ((1, 0, (5, 6)), (1, 200, (7,)), (2, 10, (5,))):
        own = spark.createDataFrame([(k,) for k in keys], "k long")
        expected += [(g, s, r["tab"], r["bin"], r["level"]) for r in cells.raw_cells(own, "k", seed).collect()]
    assert sorted(map(tuple, got)) == sorted(expected)


def test_merge_into_keeps_partitions_and_leaves_nothing(spark, tmp_path):
    import os

    from mergecount.operators import partial
    from mergecount.sources import store

    seed = seeding.init(SketchParams(3, 64, 6), "store")
    path = f"file://{tmp_path}/store"
    for keys in (range(100), range(50, 160), range(50, 160)):
        rows = spark.createDataFrame([(k % 3, k) for k in keys], "day int, k long")
        store.merge_into(partial.sketch_by(rows, "k", seed, ["day"]), path, seed, ["day"], ["day"])
    assert sorted(os.listdir(f"{tmp_path}/store/seed_fp={seed.fingerprint}")) == ["day=0", "day=1", "day=2"] and os.listdir(tmp_path) == ["store"]
    got = {r["day"]: r["estimate"] for r in store.rollup(spark, path, seed, ["day"]).collect()}
    for d in range(3):
        whole = spark.createDataFrame([(k,) for k in range(160) if k % 3 == d], "k long")
        assert got[d] == partial.estimates(partial.sketch_by(whole, "k", seed), seed).first()["estimate"]


def test_keys_of_neighbouring_columns_stay_apart(spark):
    from mergecount.functions.encode import key64, key256

    rows = spark.createDataFrame([("a\u0001b", "c"), ("a", "b\u0001c"), ("a", None)], "x string, y string")
    assert rows.select(key256(rows, "x", "y").alias("d")).distinct().count() == 3
    clock = spark.sql("select timestamp_ntz'2024-03-31 02:30:00.000001' t")
    found = []
    for zone in ("UTC", "America/New_York", "Europe/Berlin"):
        spark.conf.set("spark.sql.session.timeZone", zone)
        found.append(clock.select(key64(clock, "t")[0].alias("k")).first()["k"])
    spark.conf.set("spark.sql.session.timeZone", "UTC")
    assert found == [1711852200000001] * 3


def test_a_group_of_the_sequential_counter_gets_each_key_once(spark, monkeypatch):
    """Repeats change nothing, and do not reach the task that folds a group; null groups and null keys as before."""
    from mergecount.baselines import rough_tracked
    from mergecount.sketch import Context

    seed = seeding.init(SketchParams(3, 64, 6, budget=4.0), "repeats", "walk_16")
    rng = random.Random(3)
    rows = [(rng.choice([1, 2, None]), rng.choice([None, *range(150)]), i) for i in range(4000)]
    found = rough_tracked.by_group(spark.createDataFrame(rows, "g int, k int, o int"), "k", "o", seed, ["g"])
    for r in found.collect():
        keys = np.array([k for g, k, _ in rows if g == r["g"] and k is not None], dtype=np.uint64)
        one = rough_tracked.RoughTracked(Context.of(seed)).add(keys)
        assert (r["estimate"], r["failed_tables"], r["bits"], r["delta_bits"]) == (one.estimate(), int(one.failed.sum()), one.bits(False), one.bits(True))
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert "Aggregate" in plan and plan.index("MapInArrow") < plan.index("Aggregate")


def test_counters_share_keys_that_are_made_once(spark, sf):
    """Every method but the exact, built-in and sampled counts reads the stored keys, not the rows."""
    rows_too = ("exact", "hll_plus", "hll_sketch", "theta", "sampling")
    for name, df in experiments._all_methods(spark, sf).items():
        assert any("lineitem" in f for f in df.inputFiles()) == (name in rows_too), name


def test_a_large_update_raises_its_cut_early(monkeypatch):
    """One call hashes only some keys to bins; its state is that of many calls, and of the definition."""
    from mergecount import sketch as module

    context = Context.of(seeding.init(SketchParams(3, 64, 6), "early"))
    keys = np.arange(200_000, dtype=np.uint64) * np.uint64(experiments.ODD)
    hashed, many = [], type(context.triples[0].bins).many
    monkeypatch.setattr(type(context.triples[0].bins), "many", lambda self, x: (hashed.append(len(x)), many(self, x))[1])
    one = Sketch(context).update(keys)
    assert sum(hashed) < len(keys)
    parts = Sketch(context)
    for at in range(0, len(keys), 777):
        parts.update(keys[at : at + 777])
    assert one.pack() == parts.pack() == module.direct(context, keys).pack()


def test_a_sessions_cells_are_sorted_once(spark):
    """Not anew for every entry, which made a session of n entries take n sorts; sessions merge early only where asked."""
    from mergecount.functions.native import NativeSeed
    from mergecount.streaming import windows

    rows = spark.createDataFrame([(1, 0, 5), (1, 50, 6)], "g int, t int, k long").withColumn("at", F.timestamp_seconds("t"))
    plan = windows.session_cells(rows, "at", "k", NativeSeed(2, 64, "s"), "100 seconds", ["g"])._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("sort_array(") + plan.count("array_sort(") == 1
    name = "spark.sql.streaming.sessionWindow.merge.sessions.in.local.partition"
    was = spark.conf.get(name)
    with windows.sessions_merged_early(spark):
        assert spark.conf.get(name) == "true"
    assert spark.conf.get(name) == was


#: Queries that once made their data up or read a table beside Spark.
ON_TABLES = ("derived_sizes", "occupancy_curve", "cost_drops", "form_choice", "inverse_tables", "seed_report", "balls_thrown", "cardinality_sweep", "column_space", "cut_margin_sweep", "level_tails", "operation_counts")


@pytest.mark.parametrize("name", ON_TABLES)
def test_reads_a_given_table(spark, sf, sql, name):
    """Spark reads it, and the rows are those of the SQL."""
    con, oracles = sql
    found = workloads.queries()[name](spark, sf)
    assert any(f.endswith(("/lineitem.parquet", "/orders.parquet")) for f in found.inputFiles())
    assert plain(found.toPandas()) == plain(con.sql(oracles[name]).df())
