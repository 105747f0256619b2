"""Queries of the engine over the given tables: every method, variant, baseline, measure and workload."""

from __future__ import annotations

import atexit
import math
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bounds, cuts
from .baselines import counters
from .functions import seeding
from .functions.encode import key64
from .functions.native import NativeSeed, ideal_levels_and_bins, levels_and_bins
from .operators import cells, nested_cells, partial, rollup, setops
from .params import SketchParams, derive, independence
from .sources.tables import read
from .streaming import windows

#: Parity with SQL: pairwise bins, one fixed draw, practical sizes.
PARITY = NativeSeed(5, 256, "parity")
NESTED = nested_cells.NestedNativeSeed(3, 256, 3, "nested-parity")
OFFSET, BUDGET = 2, 1.5
FLAGS = ["l_returnflag", "l_linestatus"]
REGION = ["r_name", "n_name", "c_mktsegment"]
#: Full independence, in packed form.
KWISE = SketchParams(9, 1024, independence(1024))
TOLERANCE = 0.15


def kwise_seed() -> seeding.Seed:
    return seeding.init(KWISE, "workloads")


def _lineitem(spark: SparkSession, sf: str) -> DataFrame:
    return read(spark, sf, "lineitem")


def _customers(spark: SparkSession, sf: str) -> DataFrame:
    """Orders with the place and segment of their customer; dimensions are small and joined by broadcast when Spark's size check allows."""
    nation = read(spark, sf, "nation").join(read(spark, sf, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    customer = read(spark, sf, "customer").join(nation, F.col("c_nationkey") == F.col("n_nationkey"))
    return read(spark, sf, "orders").join(customer, F.col("o_custkey") == F.col("c_custkey")).select(*REGION, "o_custkey")


def exact_distinct_by_flag(spark, sf):
    return _lineitem(spark, sf).groupBy(*FLAGS).agg(F.countDistinct("l_partkey").alias("parts"))


def exact_bitmap(spark, sf):
    return counters.exact_bitmap(_lineitem(spark, sf), "l_partkey")


def level_histogram(spark, sf):
    keys = _lineitem(spark, sf).select("l_partkey").distinct()
    return levels_and_bins(keys, "l_partkey", PARITY, []).groupBy("tab", "level").agg(F.count("*").alias("n"))


def raw_cells(spark, sf):
    return cells.raw_cells(_lineitem(spark, sf), "l_partkey", PARITY, ["l_returnflag"])


def cut_curve(spark, sf):
    return cells.cut_curve(raw_cells(spark, sf), ["l_returnflag"])


def required_cut(spark, sf):
    return cells.required_cut(cells.raw_cells(_lineitem(spark, sf), "l_orderkey", PARITY, ["l_returnflag"]), PARITY, BUDGET, ["l_returnflag"])


def cut_cells(spark, sf):
    return cells.with_cut(cells.raw_cells(_lineitem(spark, sf), "l_orderkey", PARITY, ["l_returnflag"]), PARITY, BUDGET, ["l_returnflag"])


def _estimate(df: DataFrame, key: str, group: list[str] = (), repeated: bool = False) -> DataFrame:
    state = cells.with_cut(cells.raw_cells(df, key, PARITY, group, repeated), PARITY, BUDGET, group)
    return cells.estimate(state, PARITY, OFFSET, group)


def main_estimate_pairwise(spark, sf):
    return _estimate(_lineitem(spark, sf), "l_partkey", FLAGS, repeated=True)


def composite_estimate_pairwise(spark, sf):
    packed_key = _lineitem(spark, sf).withColumn("k", F.shiftleft(F.col("l_partkey"), 32).bitwiseOR(F.col("l_suppkey")))
    return _estimate(packed_key, "k", ["l_linestatus"])


def nested_estimate_pairwise(spark, sf):
    return nested_cells.estimate(_lineitem(spark, sf), "l_partkey", NESTED, BUDGET, OFFSET, FLAGS, repeated=True)


def merge_partitions(spark, sf):
    """Seven disjoint parts, sketched apart and merged."""
    rows = _lineitem(spark, sf)
    part = F.pmod(F.xxhash64("l_orderkey", "l_linenumber"), F.lit(7))
    by_part = cells.raw_cells(rows.withColumn("part", part), "l_partkey", PARITY, ["part"])
    return cells.union_all(by_part.drop("part"))


def merge_overlap(spark, sf):
    a = cells.raw_cells(read(spark, sf, "orders"), "o_custkey", PARITY)
    return cells.union_all(a, cells.raw_cells(read(spark, sf, "customer"), "c_custkey", PARITY))


def merge_duplicates(spark, sf):
    rows = _lineitem(spark, sf).select("l_suppkey", "l_partkey")
    return cells.raw_cells(rows.unionAll(rows).unionAll(rows), "l_partkey", PARITY)


def prune_keeps_estimate(spark, sf):
    """Estimates from pruned cells alone (no cut)."""
    raw = cells.raw_cells(_lineitem(spark, sf), "l_orderkey", PARITY, ["l_returnflag"])
    pruned = cells.prune_for_estimate(raw, PARITY, OFFSET, ["l_returnflag"]).withColumn("q", F.lit(0))
    return cells.estimate(pruned, PARITY, OFFSET, ["l_returnflag"]).drop("q")


def _cube(spark, sf, kind: str, df: DataFrame, dims: list[str], key: str) -> DataFrame:
    merged = rollup.merged_cells(cells.raw_cells(df, key, PARITY, dims), dims, kind)
    keyed = merged.withColumn("g", F.concat_ws("|", F.col("gid").cast("string"), *[F.coalesce(F.col(d), F.lit("*")) for d in dims])).select("g", "tab", "bin", "level")
    return cells.estimate(cells.with_cut(keyed, PARITY, BUDGET, ["g"]), PARITY, OFFSET, ["g"])


def cube_by_merge(spark, sf):
    return _cube(spark, sf, "cube", _lineitem(spark, sf), FLAGS, "l_partkey")


def rollup_by_merge(spark, sf):
    return _cube(spark, sf, "rollup", _customers(spark, sf), REGION, "o_custkey")


def exact_cube(spark, sf):
    """Exact yardstick of the cube."""
    return _lineitem(spark, sf).cube(*FLAGS).agg(F.countDistinct("l_partkey").alias("parts"), F.grouping_id().cast("int").alias("gid"))


def top_segments(spark, sf):
    """The five nation and segment pairs with the most estimated customers."""
    found = _estimate(_customers(spark, sf), "o_custkey", ["n_name", "c_mktsegment"])
    return found.orderBy(F.desc("estimate"), "n_name", "c_mktsegment").limit(5)


OCCUPANCY = (("customer", "orders", "o_custkey"), ("part", "lineitem", "l_partkey"), ("supplier", "lineitem", "l_suppkey"))


def occupancy_curve(spark, sf):
    """Expected hits of r balls and balls for r hits, for every number r of orders that customers, and of lines that parts and suppliers, have."""
    b = 256
    many = None
    for kind, table, key in OCCUPANCY:
        rows = read(spark, sf, table).filter(F.col(key).isNotNull()).groupBy(key).agg(F.count("*").alias("r")).groupBy("r").agg(F.count("*").alias("owners")).select(F.lit(kind).alias("kind"), "r", "owners")
        many = rows if many is None else many.union(rows)
    curve = F.lit(b) * (1 - F.pow(F.lit(1 - 1 / b), F.col("r")))
    back = F.log(1 - F.least(F.col("r"), F.lit(b - 1)) / F.lit(float(b))) / F.log(F.lit(1 - 1 / b))
    return many.select("kind", "r", "owners", F.round(curve, 6).alias("hits"), F.round(F.abs(back), 6).alias("balls"))


def worked_example_cut(spark, sf):
    rows = [(c, int(cuts.cell_bits(max(23 - c, -1)))) for c in range(26)]
    return spark.createDataFrame(rows, "cut int, bits int")


GRID = [(bits, eps, delta) for bits in (32, 64, 256) for eps in (0.1, 0.01) for delta in (0.1, 1e-6)]


def space_table(spark, sf):
    rows = [(name, bits, eps, delta, round(bounds.space_formula(name, bits, eps, delta), 3)) for name in bounds.SPACE for bits, eps, delta in GRID]
    return spark.createDataFrame(rows, "algorithm string, bits int, eps double, delta double, formula double")


ACCURACIES = ((0.5, 0.1), (0.1, 0.05), (0.01, 0.01))


def derived_sizes(spark, sf):
    """The proof's sizes for the keys of each flag's parts: bits of the largest key, and whether one sketch will do (delta >= 1 / ln n) or copies are needed."""
    widths = _lineitem(spark, sf).filter("l_partkey is not null").groupBy("l_returnflag").agg(F.length(F.bin(F.max("l_partkey"))).alias("bits"))
    rows = [(eps, delta, p.l, p.log_b, p.profile) for eps, delta in ACCURACIES for p in [derive(64, eps, delta)]]  # tables and bins do not depend on the keys' bits
    sizes = spark.createDataFrame(rows, "eps double, delta double, l int, log_b int, profile string")
    return widths.join(F.broadcast(sizes)).select("l_returnflag", "bits", "eps", "delta", "l", "log_b", "profile", (F.col("delta") * F.col("bits") * math.log(2) >= 1).alias("single"))


TAILS = [(mu, lam, g, l) for mu in (0.02, 0.1) for lam in (0.0, 0.003) for g in (0.3, 0.5) for l in (8, 32)]


def tail_bounds_grid(spark, sf):
    rows = [(mu, lam, g, l, *(round(x, 9) for x in (bounds.kl(g, mu + lam), bounds.tail_kl(mu, lam, g, l), bounds.tail_log(mu, lam, g, l), bounds.tail_quadratic(mu, lam, g, l), bounds.hitting(mu, lam, 4)[0], bounds.deviation(l), bounds.median_failure(l)))) for mu, lam, g, l in TAILS]
    return spark.createDataFrame(rows, "mu double, lam double, g double, l int, kl double, tail_kl double, tail_log double, tail_quadratic double, hitting double, deviation double, median_failure double")


def bitpattern_baseline(spark, sf):
    return counters.bit_pattern(_lineitem(spark, sf), "l_orderkey", PARITY, ["l_returnflag"])


def maxlevel_baseline(spark, sf):
    return counters.max_level(_lineitem(spark, sf), "l_orderkey", PARITY, ["l_returnflag"])


def binned_levels_baseline(spark, sf):
    return counters.binned_levels(_lineitem(spark, sf), "l_orderkey", PARITY, ["l_returnflag"])


def sketch_bits(spark, sf):
    return cells.size_bits(cut_cells(spark, sf), PARITY, ["l_returnflag"])


def exact_overlap(spark, sf):
    return setops.exact_overlap(read(spark, sf, "customer"), read(spark, sf, "orders").filter("o_orderstatus = 'F'"), "c_custkey", "o_custkey")


def keys_without_orders(spark, sf):
    """Semi and anti joins as exact yardsticks."""
    customer, orders = read(spark, sf, "customer"), read(spark, sf, "orders").filter("o_totalprice > 300000")
    some = customer.join(orders, F.col("c_custkey") == F.col("o_custkey"), "left_semi").groupBy("c_mktsegment").agg(F.count("*").alias("with_orders"))
    none = customer.join(orders, F.col("c_custkey") == F.col("o_custkey"), "left_anti").groupBy("c_mktsegment").agg(F.count("*").alias("without"))
    return some.join(none, "c_mktsegment", "full_outer").select("c_mktsegment", F.coalesce("with_orders", F.lit(0)).alias("with_orders"), F.coalesce("without", F.lit(0)).alias("without"))


def adversarial_split(spark, sf):
    """Process 0 sees many keys, the others only the last one: every process, and the merge."""
    last = read(spark, sf, "lineitem").agg(F.max("l_orderkey").alias("k"))
    many = _lineitem(spark, sf).select(F.lit(0).alias("process"), F.col("l_orderkey").alias("k"))
    copies = last.select(F.explode(F.sequence(F.lit(1), F.lit(7))).alias("process"), "k")
    each = cells.raw_cells(many.unionByName(copies), "k", PARITY, ["process"])
    merged = cells.union_all(each.drop("process")).withColumn("process", F.lit(-1))
    both = each.select("process", "tab", "bin", "level").unionByName(merged.select("process", "tab", "bin", "level"))
    return cells.estimate(cells.with_cut(both, PARITY, BUDGET, ["process"]), PARITY, OFFSET, ["process"])


def window_distinct_exact(spark, sf):
    events = read(spark, sf, "events")
    tumbling = events.groupBy(F.window("ts", "1 day")).agg(F.countDistinct("user_id").alias("users")).select(F.lit("tumbling").alias("kind"), F.col("window.start").cast("string").alias("day"), "users")
    sliding = events.groupBy(F.window("ts", "2 days", "1 day")).agg(F.countDistinct("user_id").alias("users")).select(F.lit("sliding").alias("kind"), F.col("window.start").cast("string").alias("day"), "users")
    return tumbling.union(sliding)


def window_distinct_pairwise(spark, sf):
    """Users of each event type and day, from merged cells."""
    state = windows.window_cells(read(spark, sf, "events"), "ts", "user_id", PARITY, "1 day")
    return windows.window_estimates(state, PARITY, BUDGET, OFFSET).select(F.col("window_start").cast("string").alias("day"), "estimate", "q")


def longer_windows_by_merge(spark, sf):
    """Windows of five days merged from stored days."""
    daily = windows.window_cells(read(spark, sf, "events"), "ts", "user_id", PARITY, "1 day")
    state = windows.longer_windows(daily, "5 days")
    return windows.window_estimates(state, PARITY, BUDGET, OFFSET).select(F.col("window_start").cast("string").alias("day"), "estimate", "q")


def json_key_distinct(spark, sf):
    """Distinct values of a JSON field, with a filtered count beside it."""
    k = F.get_json_object("props", "$.k")
    return read(spark, sf, "events").groupBy("event_type").agg(F.countDistinct(k).alias("keys"), F.countDistinct(F.when(F.col("value") > 10, k)).alias("keys_above"))


def two_pass_estimate(spark, sf):
    """Estimates from thresholds first, then only the cells above them."""
    state = cells.two_pass_cells(_lineitem(spark, sf), "l_orderkey", PARITY, OFFSET, ["l_returnflag"]).withColumn("q", F.lit(0))
    return cells.estimate(state, PARITY, OFFSET, ["l_returnflag"]).drop("q")


def running_distinct_by_merge(spark, sf):
    """Users up to the end of each day, from daily cells merged forward."""
    events = read(spark, sf, "events").withColumn("step", F.datediff(F.col("ts").cast("date"), F.lit("2024-01-01").cast("date")))
    last = events.agg(F.coalesce(F.max("step"), F.lit(0))).first()[0]
    merged = cells.prefix_merges(cells.raw_cells(events, "user_id", PARITY, ["step"]), "step", last)
    return cells.estimate(cells.with_cut(merged, PARITY, BUDGET, ["step"]), PARITY, OFFSET, ["step"])


# -- tolerance form: exact, and whether the sketch is within TOLERANCE ------------------------------------


def _within(found: DataFrame, exact: DataFrame, group: list[str]) -> DataFrame:
    joined = found.join(exact, group) if group else found.select("estimate").limit(1).withColumn("_one", F.lit(1)).join(exact.withColumn("_one", F.lit(1)), "_one")
    return joined.select(*group, "exact", (F.abs(F.col("estimate") - F.col("exact")) <= TOLERANCE * F.col("exact")).alias("within"))


def _packed_within(df: DataFrame, key: str, group: list[str]) -> DataFrame:
    seed = kwise_seed()
    return _within(partial.estimates(partial.sketch_by(df, key, seed, group), seed), df.groupBy(*group).agg(F.countDistinct(key).alias("exact")), group)


def kwise_within(spark, sf):
    return _packed_within(_lineitem(spark, sf), "l_partkey", ["l_returnflag"])


def main_within(spark, sf):
    return _packed_within(_lineitem(spark, sf), "l_orderkey", [])


def skew_within(spark, sf):
    orders = read(spark, sf, "orders")
    key, _ = key64(orders, "o_orderstatus")
    return _packed_within(orders.select(key.alias("k")), "k", [])


def double_key_within(spark, sf):
    rows = _lineitem(spark, sf)
    key, _ = key64(rows, "l_extendedprice")
    return _packed_within(rows.select(key.alias("k")), "k", [])


def tokens_within(spark, sf):
    docs = read(spark, sf, "documents")
    words = docs.select(F.explode(F.split(F.lower("text"), "[ \\t\\n\\r\\x0b\\x0c]+")).alias("w")).filter("w <> ''").select("w", F.xxhash64("w").alias("k"))
    seed = kwise_seed()
    return _within(partial.estimates(partial.sketch_by(words, "k", seed), seed), words.agg(F.countDistinct("w").alias("exact")), [])


def texts_within(spark, sf):
    """Distinct texts by language: copies do not count."""
    docs = read(spark, sf, "documents").select("lang", "text", F.xxhash64("text").alias("k"))
    seed = kwise_seed()
    return _within(partial.estimates(partial.sketch_by(docs, "k", seed, ["lang"]), seed), docs.groupBy("lang").agg(F.countDistinct("text").alias("exact")), ["lang"])


def union_within(spark, sf):
    seed = kwise_seed()
    a = partial.sketch_by(read(spark, sf, "orders").filter("o_orderstatus = 'F'").select(F.col("o_custkey").alias("k")), "k", seed)
    b = partial.sketch_by(read(spark, sf, "customer").select(F.col("c_custkey").alias("k")), "k", seed)
    exact = read(spark, sf, "customer").select(F.col("c_custkey").alias("k")).union(read(spark, sf, "orders").filter("o_orderstatus = 'F'").select("o_custkey")).agg(F.countDistinct("k").alias("exact"))
    return _within(partial.estimates(partial.merge_by(a.union(b), seed), seed), exact, [])


def seq_equals_par(spark, sf):
    """One task in order of arrival, or 1, 2, 7 and 64 parts: one state, byte for byte."""
    seed = kwise_seed()
    events = read(spark, sf, "events").select("event_id", F.col("user_id"))
    forms = [events.coalesce(1).sortWithinPartitions("event_id"), *[events.repartition(p) for p in (1, 2, 7, 64)]]
    out = None
    for i, form in enumerate(forms):
        one = partial.sketch_by(form, "user_id", seed).select(F.lit(i).alias("form"), F.sha2("sketch", 256).alias("digest"))
        out = one if out is None else out.union(one)
    return out.agg(F.count("*").alias("forms"), F.countDistinct("digest").alias("states"))


def ideal_hash_within(spark, sf):
    """Levels and bins from xxHash in place of the explicit families."""
    state = ideal_levels_and_bins(_lineitem(spark, sf), "l_partkey", 9, 1024, ["l_returnflag"]).groupBy("l_returnflag", "tab", "bin").agg(F.max("level").alias("level"))
    seed = NativeSeed(9, 1024, "ideal")
    found = cells.estimate(cells.with_cut(state, seed, BUDGET, ["l_returnflag"]), seed, OFFSET, ["l_returnflag"])
    return _within(found, _lineitem(spark, sf).groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("exact")), ["l_returnflag"])


def stream_within(spark, sf):
    """Daily users from a streaming query over the events, replayed batches included."""
    source = read(spark, sf, "events")
    base = shared_folder(spark) + f"/mergecount-stream-{uuid.uuid4().hex}"
    source.select("ts", "user_id").repartition(3).write.parquet(f"{base}/in")
    stream = spark.readStream.schema(spark.read.parquet(f"{base}/in").schema).option("maxFilesPerTrigger", 1).parquet(f"{base}/in")
    state = windows.window_cells(stream, "ts", "user_id", PARITY, "1 day", late="40 days")

    def sink(batch: DataFrame, no: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/out/batch={no}")

    windows.start(state, PARITY, f"{base}/checkpoint", sink).awaitTermination()
    merged = spark.read.parquet(f"{base}/out").groupBy("window", "tab", "bin").agg(F.max("level").alias("level"))
    found = windows.window_estimates(merged, PARITY, BUDGET, OFFSET).select(F.col("window_start").cast("string").alias("day"), "estimate")
    exact = source.groupBy(F.window("ts", "1 day")).agg(F.countDistinct("user_id").alias("exact")).select(F.col("window.start").cast("string").alias("day"), "exact")
    joined = found.join(exact, "day")
    return joined.select("day", "exact", (F.abs(F.col("estimate") - F.col("exact")) <= 0.5 * F.col("exact")).alias("within"))


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share (spark.checkpoint.dir); a temporary one only where it is unset."""
    sc = spark.sparkContext
    path = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir")
    if path:
        return path
    known = sc._jsc.sc().getCheckpointDir()
    if known.isDefined():
        return known.get()
    own = tempfile.mkdtemp(prefix="mergecount-")
    atexit.register(shutil.rmtree, own, True)
    sc.setCheckpointDir(own)
    return own


# -- rows only -----------------------------------------------------------------------------------------------


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return main_estimate_pairwise(spark, sf_dir)


QUERIES = (
    exact_distinct_by_flag, exact_bitmap, level_histogram, raw_cells, cut_curve, required_cut, cut_cells, main_estimate_pairwise, composite_estimate_pairwise,
    nested_estimate_pairwise, merge_partitions, merge_overlap, merge_duplicates, prune_keeps_estimate, cube_by_merge, rollup_by_merge, exact_cube, top_segments,
    occupancy_curve, worked_example_cut, space_table, derived_sizes, tail_bounds_grid, bitpattern_baseline, maxlevel_baseline, binned_levels_baseline, sketch_bits,
    exact_overlap, keys_without_orders, adversarial_split, window_distinct_exact, window_distinct_pairwise, longer_windows_by_merge, json_key_distinct, two_pass_estimate, running_distinct_by_merge,
    kwise_within, main_within, skew_within, double_key_within, tokens_within, texts_within, union_within, seq_equals_par, ideal_hash_within, stream_within,
)


def queries() -> dict:
    from .experiments import QUERIES as MORE

    return {q.__name__: q for q in (*QUERIES, *MORE)}


def oracle_sql() -> dict[str, str]:
    from .experiments_sql import ORACLES as MORE
    from .workloads_sql import ORACLES

    return {**ORACLES(), **MORE()}


