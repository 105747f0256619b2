"""Experiments: sweeps of size, accuracy, cuts, walks, events and costs, and all counters side by side."""

from __future__ import annotations

import json
import math
import uuid
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bounds, cuts, nested
from .baselines import counters
from .baselines.rough_tracked import by_group
from .functions import seeding
from .functions.encode import key64
from .functions.expander import Graph
from .functions.native import NativeSeed, levels_and_bins
from .operators import cells, nested_cells, ordered, partial, rollup, setops
from .params import SketchParams, independence
from .plans.planner import shuffled
from .sketch import Sketch, rho_inv_table
from .sources import store
from .sources.tables import read
from .streaming import windows
from .workloads import BUDGET, FLAGS, KWISE, NESTED, OFFSET, PARITY, _lineitem, _within, kwise_seed, shared_folder

#: An odd constant that spreads keys.
ODD = 2654435761
#: Sets of the sweeps over sizes: the keys of a table that 2^share divides, from all of them down.
SHARES = tuple(range(13))
#: Many tables at once, for frequencies of events.
MANY = NativeSeed(64, 256, "frequencies")
TAIL_SHIFTS = tuple(range(1, 9))
PROCESSES = (1, 8, 64)
WALK_LENGTHS, WALKS, WALK_LAMBDA = (4, 8, 16), 4000, 1 / 16


def _sized(spark: SparkSession, sf: str, key: str) -> DataFrame:
    """(share, k): the distinct keys of a column of lineitem that 2^share divides, for every share; twice as many rows as keys."""
    keys = _lineitem(spark, sf).filter(F.col(key).isNotNull()).select(F.col(key).cast("long").alias("k")).distinct()
    in_sets = F.array_compact(F.array(*[F.when(F.pmod("k", F.lit(1 << j)) == 0, F.lit(j)) for j in SHARES]))
    return keys.select(F.explode(in_sets).alias("share"), "k")


def _sizes(sized: DataFrame) -> DataFrame:
    """(share, size): how many keys each set has."""
    return sized.groupBy("share").agg(F.count("*").alias("size"))


def _width(key) -> Column:
    """Bits of the largest key of a column."""
    return F.length(F.bin(F.max(key)))


# -- sizes, cuts, costs: parity with SQL -----------------------------------------------------------------------


def cardinality_sweep(spark, sf):
    """Sets of order keys through the regimes of cut and threshold: estimate, cut, least and largest threshold of the tables."""
    sized = _sized(spark, sf, "l_orderkey")
    raw = cells.raw_cells(sized, "k", PARITY, ["share"])
    state = cells.with_cut(raw, PARITY, BUDGET, ["share"])
    found = cells.estimate(state, PARITY, OFFSET, ["share"])
    top = raw.groupBy("share", "tab").agg(F.greatest(F.lit(0), F.max("level") - (PARITY.b.bit_length() - 1) + OFFSET).alias("s"))
    ends = top.groupBy("share").agg(F.min("s").alias("s_min"), F.max("s").alias("s_max"))
    return found.join(ends, "share").join(_sizes(sized), "share").select("share", "size", "estimate", "q", "s_min", "s_max", (F.col("q") <= F.col("s_min")).alias("cut_ok"))


def cut_margin_sweep(spark, sf):
    """The cut of sets of order keys against the level that it stays below but for a small chance."""
    sized = _sized(spark, sf, "l_orderkey")
    q = cells.required_cut(cells.raw_cells(sized, "k", PARITY, ["share"]), PARITY, BUDGET, ["share"]).join(_sizes(sized), "share")
    most = F.greatest(F.lit(0), F.ceil(F.log2(F.col("size"))).cast("int") - (PARITY.b.bit_length() - 1))
    return q.select("share", "size", "q", most.alias("q_max"), (F.col("q") <= most + math.ceil(math.log2(8 / BUDGET))).alias("q_near"))


def column_space(spark, sf):
    """Bits of each table of sets of parts at the state's cut, and the share of tables over (c + 3) bits a bin beside its bound."""
    v = F.col("level") + 2
    width = sum((F.when(v >= 2**i, 1).otherwise(0) for i in range(1, 7)), F.lit(0))
    sized = _sized(spark, sf, "l_partkey")
    state = cells.with_cut(cells.raw_cells(sized, "k", MANY, ["share"]), MANY, BUDGET, ["share"])
    tables = state.groupBy("share", "tab").agg(F.sum(width).alias("bits"))
    c = F.explode(F.array(*[F.lit(x) for x in range(-2, 3)])).alias("c")
    over = (F.col("bits") > (F.col("c") + 3) * MANY.b).cast("int")
    found = tables.select("share", "bits", c).groupBy("share", "c").agg(F.max("bits").alias("most_bits"), F.round(F.sum(over) / MANY.l, 6).alias("over_share"))
    bound = F.when(F.col("c") >= 0, F.round(F.pow(F.lit(2.0), -F.pow(F.lit(2.0), F.col("c"))), 9)).otherwise(F.lit(1.0))
    return found.join(_sizes(sized), "share").select("share", "size", "c", "most_bits", "over_share", bound.alias("bound"))


def operation_counts(spark, sf):
    """Input of a one-shot cut of sets of order keys (the cost of all cells before it), and the operations: cells, levels of the histogram, candidates."""
    v = F.col("level") + 2
    width = sum((F.when(v >= 2**i, 1).otherwise(0) for i in range(1, 7)), F.lit(0))
    sized = _sized(spark, sf, "l_orderkey")
    found = cells.raw_cells(sized, "k", PARITY, ["share"]).groupBy("share").agg(F.sum(width).alias("input_bits"), F.count("*").alias("cells"), F.countDistinct("level").alias("levels"), F.max("level").alias("_top"))
    return found.join(_sizes(sized), "share").select("share", "size", "input_bits", "cells", "levels", ((F.col("_top") + 2) * F.col("levels")).alias("candidates"))


def level_tails(spark, sf):
    """How often the largest level of a set of n parts is over ld n + k or below ld n - k - 1, over many tables, beside the bound 2^-k."""
    sized = _sized(spark, sf, "l_partkey")
    top = levels_and_bins(sized, "k", MANY, ["share"]).groupBy("share", "tab").agg(F.max("level").alias("top")).join(_sizes(sized), "share")
    shift = top.select("size", "top", F.explode(F.array(*[F.lit(k) for k in TAIL_SHIFTS])).alias("k"))
    ld = F.log2(F.col("size"))
    off = ((F.col("top") > ld + F.col("k")) | (F.col("top") < ld - F.col("k") - 1)).cast("int")
    return shift.groupBy("k").agg(F.sum(off).alias("off"), F.count("*").alias("tables")).select("k", "off", "tables", F.pow(F.lit(2.0), -F.col("k")).alias("bound"), (F.col("off") / F.col("tables") <= 2 * F.pow(F.lit(2.0), -F.col("k"))).alias("within"))


def event_frequencies(spark, sf):
    """The events of the analysis in each of many tables, on the distinct parts: computed where the rows are."""
    keys = _lineitem(spark, sf).filter("l_partkey is not null").select("l_partkey").distinct()
    b, log_b = MANY.b, MANY.b.bit_length() - 1
    rows = levels_and_bins(keys, "l_partkey", MANY, [])
    tops = rows.groupBy("tab").agg(F.max("level").alias("top"), F.count("*").alias("n")).select("tab", "n", F.greatest(F.lit(0), F.col("top") - log_b + OFFSET).alias("s"))
    sampled = rows.join(F.broadcast(tops), "tab").filter("level >= s").groupBy("tab", "n", "s").agg(F.count("*").alias("r"), F.countDistinct("bin").alias("hits"))
    load = F.col("n") / F.pow(F.lit(2.0), F.col("s"))
    rho = b * (1 - F.pow(F.lit(1 - 1 / b), F.col("r")))
    back = lambda h: F.log(1 - F.least(h, F.lit(b - 1)) / F.lit(float(b))) / F.log(F.lit(1 - 1 / b))
    return sampled.select(
        "tab", "s", "r", "hits",
        ((F.col("s") == 0) | load.between(2.0**-16 * b, b / 2)).alias("load_ok"),
        (F.abs(F.col("r") - load) <= 0.5 / 3 * load).alias("sample_ok"),
        (F.abs(F.col("hits") - rho) <= 9 * F.col("r") / math.sqrt(b)).alias("hits_ok"),
        (F.col("r") <= 2 * b / 3).alias("sample_small"), (F.col("hits") <= 41 * b / 60).alias("hits_small"),
        (back(F.col("hits") + 1) - back(F.col("hits")) < 4).alias("slope_ok"),
    )


def balls_thrown(spark, sf):
    """Bins hit by sets of r parts in each of many tables: mean, least and most, beside the occupancy curve."""
    sized = _sized(spark, sf, "l_partkey")
    hits = levels_and_bins(sized, "k", MANY, ["share"]).groupBy("share", "tab").agg(F.countDistinct("bin").alias("hits"))
    found = hits.groupBy("share").agg(F.round(F.avg("hits"), 6).alias("mean_hits"), F.min("hits").alias("least"), F.max("hits").alias("most"))
    curve = MANY.b * (1 - F.pow(F.lit(1 - 1 / MANY.b), F.col("size")))
    return found.join(_sizes(sized), "share").select("share", F.col("size").alias("r"), "mean_hits", "least", "most", F.round(curve, 6).alias("curve"))


def cost_drops(spark, sf):
    """Cuts at which the cells of each level of a sketch of the order keys get a bit cheaper, and how many cells these are."""
    levels = cells.raw_cells(_lineitem(spark, sf), "l_orderkey", PARITY, repeated=True).groupBy("level").agg(F.count("*").alias("cells"))
    drops = F.from_json(F.lit(json.dumps([cuts.cost_drops(v) for v in range(cells.TOP + 1)])), F.lit("array<array<int>>"))
    return levels.select("level", "cells", F.explode(F.get(drops, F.col("level"))).alias("cut"))


def cut_forms_agree(spark, sf):
    """The cut of real cells by the relational form, the one-shot form and step by step."""
    group = "l_returnflag"
    raw = cells.raw_cells(_lineitem(spark, sf), "l_orderkey", PARITY, [group])
    limit = math.floor(BUDGET * PARITY.l * PARITY.b)

    def both(pdf):
        import pandas as pd

        levels = np.full((PARITY.l, PARITY.b), -1, dtype=np.int8)
        levels[pdf["tab"], pdf["bin"]] = pdf["level"]
        _, steps = cuts.compress_stepwise(levels, 0, limit)
        return pd.DataFrame({group: [pdf[group].iloc[0]], "one_shot": [cuts.required_cut(levels, limit)], "stepwise": [steps]})

    plain = raw.groupBy(group).applyInPandas(both, f"{group} string, one_shot int, stepwise int")  # a group has l x b cells at most
    q = cells.required_cut(raw, PARITY, BUDGET, [group])
    return q.join(plain, group).select(group, "q", ((F.col("q") == F.col("one_shot")) & (F.col("q") == F.col("stepwise"))).alias("agree"))


def estimate_at_any_cut(spark, sf):
    """Estimates of one set of cells at its cut and at the cuts above it."""
    group = "l_returnflag"
    raw = cells.raw_cells(_lineitem(spark, sf), "l_orderkey", PARITY, [group])
    q = cells.required_cut(raw, PARITY, BUDGET, [group])
    higher = q.select(group, F.explode(F.sequence(F.col("q"), F.col("q") + 3)).alias("q"))
    state = raw.join(higher, group).select(group, F.col("q").alias("cut"), "tab", "bin", (F.col("level") - F.col("q")).cast("int").alias("level"), "q").filter("level >= 0")
    return cells.estimate(state, PARITY, OFFSET, [group, "cut"]).select(group, "cut", "estimate")


def cut_sharing_ablation(spark, sf):
    """Nested cells with one cut for all copies, one for each copy, or one for each table: estimate, range of the cuts and their bits."""
    raw = nested_cells.raw_cells(_lineitem(spark, sf), "l_orderkey", NESTED, [])
    raw = raw.withColumn("t", F.col("copy") * NESTED.l + F.col("tab"))
    out = None
    for kind, group, tables in (("shared", [], NESTED.l * NESTED.m), ("copy", ["copy"], NESTED.l), ("table", ["t"], 1)):
        q = cells.required_cut(raw, NativeSeed(tables, NESTED.b, NESTED.entropy), BUDGET, group)
        joined = raw.join(q, group) if group else raw.join(F.broadcast(q.limit(1)))
        state = joined.select("copy", "tab", "bin", (F.col("level") - F.col("q")).cast("int").alias("level"), "q").filter("level >= 0")
        inner = cells.estimate(state, NESTED.inner(), OFFSET, ["copy"], "inner")
        cut = q.agg(F.min("q").alias("q_min"), F.max("q").alias("q_max")).withColumn("cuts", F.lit(kind))
        one = inner.agg(F.round(F.median("inner"), 6).alias("estimate")).withColumn("cuts", F.lit(kind)).join(cut, "cuts").withColumn("cut_bits", F.lit(nested.cut_bits(kind, NESTED.m, NESTED.l)))
        out = one if out is None else out.unionByName(one)
    return out.select("cuts", "estimate", "q_min", "q_max", "cut_bits")


def communication_measured(spark, sf):
    """Bits that p processes send at the end (cells in the self-delimiting code, and the cut), beside their merge's."""
    rows = _lineitem(spark, sf)
    out = None
    for p in PROCESSES:
        part = rows.select(F.pmod("l_orderkey", F.lit(p)).alias("part"), "l_partkey")
        sent = cells.size_bits(cells.with_cut(cells.raw_cells(part, "l_partkey", PARITY, ["part"]), PARITY, BUDGET, ["part"]), PARITY, ["part"])
        one = sent.agg(F.lit(p).alias("processes"), F.count("*").alias("sketches"), F.sum("cell_bits").alias("end_bits"), F.max("cell_bits").alias("most_bits"))
        out = one if out is None else out.unionByName(one)
    return out


SEED_KEYS = ("l_orderkey", "l_partkey", "l_suppkey")


def seed_report(spark, sf):
    """Seed bits by mode and size, for keys of as many bits as those of lineitem have."""
    widths = _lineitem(spark, sf).agg(*[_width(c).alias(c) for c in SEED_KEYS])
    each = widths.select(F.explode(F.array(*[F.struct(F.lit(c).alias("key"), F.col(c).alias("bits")) for c in SEED_KEYS])).alias("x")).select("x.key", "x.bits").filter("bits is not null")
    rows = []
    for log_b in (8, 10, 12):
        for l in (9, 12):
            sized = [SketchParams(l, 2**log_b, independence(2**log_b), d) for d in range(1, 65)]
            rows += [(log_b, l, mode, [seeding.seed_bits(p, mode) for p in sized]) for mode in seeding.MODES]
    sizes = spark.createDataFrame(rows, "log_b int, l int, mode string, by_bits array<long>")
    return each.join(F.broadcast(sizes)).select("key", "bits", "log_b", "l", "mode", F.get("by_bits", F.col("bits") - 1).alias("seed_bits"))


FORM_TASKS = (8, 1000, 100_000)
#: Groupings of lineitem whose groups are counted.
FORM_GROUPS = (("all", []), ("flag", ["l_returnflag"]), ("flags", FLAGS), ("day", ["l_shipdate"]), ("day_flags", ["l_shipdate", *FLAGS]))


def form_choice(spark, sf):
    """Shuffled bytes of both forms for growing task counts and the groups that lineitem has."""
    met = _lineitem(spark, sf).select("l_shipdate", *FLAGS).distinct()
    counted = [met.select(*columns, F.lit(1).alias("_one")).distinct().agg(F.lit(name).alias("grouping"), F.count("*").alias("groups")) for name, columns in FORM_GROUPS]
    each = reduce(DataFrame.unionByName, counted).withColumn("tasks", F.explode(F.array(*[F.lit(t) for t in FORM_TASKS])))
    cell_bytes, packed = shuffled(KWISE, F.col("groups") * F.col("tasks"))
    return each.select("grouping", "groups", "tasks", F.when(cell_bytes <= packed, "cells").otherwise("packed").alias("form"), cell_bytes.alias("cell_bytes"), F.floor(packed).alias("packed_bytes"))


MORE_TAILS = [(mu, lam, g, l) for mu in (0.1, 0.2) for lam in (0.001, 0.01) for g in (0.25, 0.3) for l in (8, 32)]


def tail_bounds_more(spark, sf):
    """The older divergence bound, both hitting bounds, the gap bound, the simple divergence and the repetitions it gives."""
    rows = [(mu, lam, g, l, *(round(x, 9) for x in (bounds.tail_kl_2010(mu, lam, g, l), *bounds.hitting(mu, lam, 3), bounds.tail_gap(g, lam, l), bounds.kl_lower(g, mu + lam))), bounds.repetitions(mu, 1e-6), bounds.tail_kl(mu, lam, mu + g, l) <= bounds.tail_kl_2010(mu, lam, g, l)) for mu, lam, g, l in MORE_TAILS]
    return spark.createDataFrame(rows, "mu double, lam double, g double, l int, older double, hitting_exact double, hitting double, gap double, kl_lower double, repetitions int, sharper boolean")


INVERSE = NativeSeed(5, 1 << 14, "inverse")
INVERSE_SIZES = tuple((log_b, factor) for log_b in (8, 10, 12) for factor in (1, 4))


def inverse_tables(spark, sf):
    """The approximate inverse of the occupancy curve at b and at 4 b bins on the parts of each flag: its size, the hits looked up, and whether the largest relative error is small.

    Keys are hashed once to the most bins; fewer bins are the low bits of these.
    """
    group, tolerance = "l_returnflag", 0.01
    fine = cells.raw_cells(_lineitem(spark, sf), "l_partkey", INVERSE, [group], repeated=True)
    tables = [rho_inv_table(factor << log_b, tolerance).tolist() for log_b, factor in INVERSE_SIZES]
    shapes = [(log_b, factor, (factor << log_b).bit_length() - 1, len(t), independence(factor << log_b), t) for (log_b, factor), t in zip(INVERSE_SIZES, tables, strict=True)]
    shapes = spark.createDataFrame(shapes, "log_b int, factor int, bits int, entries int, independence int, inverse array<double>")
    bits = F.explode(F.array(*[F.lit(x) for x in sorted({(f << k).bit_length() - 1 for k, f in INVERSE_SIZES})])).alias("bits")
    of_size = fine.select(group, "tab", "bin", "level", bits).groupBy(group, "bits", "tab", F.expr("bin & (shiftleft(1, bits) - 1)").alias("bin")).agg(F.max("level").alias("level"))
    counts = of_size.groupBy(group, "bits", "tab", "level").agg(F.count("*").alias("n"))
    tops = counts.groupBy(group, "bits", "tab").agg(F.greatest(F.lit(0), F.max("level") - F.col("bits") + OFFSET).alias("s"))
    hits = counts.join(tops, ["bits", "tab"] + [group]).filter("level >= s").groupBy(group, "bits", "tab").agg(F.sum("n").alias("hits"))
    b = F.pow(F.lit(2.0), F.col("bits"))
    exact = F.log(1 - F.least(F.col("hits").cast("double"), b - 1) / b) / F.log(1 - 1 / b)
    near = F.coalesce(F.get("inverse", F.col("hits").cast("int")), exact)  # hits beyond the table are exact
    found = hits.join(F.broadcast(shapes), "bits").select(group, "log_b", "factor", "entries", "independence", "hits", (F.abs(near - exact) / exact).alias("error"))
    return found.groupBy(group, "log_b", "factor", "entries", "independence").agg(F.min("hits").alias("least"), F.max("hits").alias("most"), (F.max("error") <= tolerance).alias("within"))


# -- joins by order ----------------------------------------------------------------------------------------------


def asof_purchase_view(spark, sf):
    """The last view of its user at or before each purchase."""
    events = read(spark, sf, "events").select("event_id", "ts", "user_id", "event_type")
    views = events.filter("event_type = 'view'").select("user_id", "ts", F.col("event_id").alias("view_id"))
    found = ordered.asof_join(events.filter("event_type = 'purchase'").select("user_id", "ts", "event_id"), views, ["user_id"], "ts", F.col("ts").cast("date"), ["view_id"])
    return found.select("event_id", F.col("asof_view_id").alias("view_id"))


def distinct_in_ranges(spark, sf):
    """Distinct parts bought in each of some ranges of order keys, from an interval join."""
    ranges = spark.range(8).select(F.col("id").alias("r"), (F.col("id") * 700).alias("lo"), (F.col("id") * 700 + 1000).alias("hi"))
    joined = ordered.interval_join(_lineitem(spark, sf).select("l_orderkey", "l_partkey"), ranges, "l_orderkey", "lo", "hi", 512)
    return joined.groupBy("r").agg(F.countDistinct("l_partkey").alias("parts"), F.count("*").alias("rows"))


# -- estimates against exact counts ------------------------------------------------------------------------------

METHODS = (
    ("exact", True, 0.0), ("single_cut", True, 0.15), ("single_cut_independent", True, 0.15), ("single_tiny_delta", True, 0.2), ("nested", True, 0.2), ("pairwise_bins", True, 0.6),
    ("bit_pattern", True, 0.3), ("max_level", True, 3.0), ("binned_levels", True, 0.6), ("rough_tracked", False, 0.4), ("walk_seeded", False, 0.4),
    ("hll_plus", True, 0.1), ("hll_sketch", True, 0.1), ("theta", True, 0.1), ("sampling", False, 1.0),
)
#: Sizes of the single sketch for a failure probability of 1e-6, and of the copies of the nested one.
TINY = SketchParams(59, 256, 8)
NESTED_PARAMS = nested.derive_nested(64, 0.3, 1e-6, inner=SketchParams(5, 256, 8))


def _stored(df: DataFrame, name: str) -> DataFrame:
    """Written to the shared folder and read again, so that many readers make it once and their plans stay small."""
    path = shared_folder(df.sparkSession) + f"/mergecount-{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def _first_seen(df: DataFrame, key: str) -> DataFrame:
    """(key, o): every key once, with the number of its first row; stored."""
    rows = df.filter(F.col(key).isNotNull()).select(key, F.monotonically_increasing_id().alias("o"))
    return _stored(rows.groupBy(key).agg(F.min("o").alias("o")), "keys")


def _all_methods(spark, sf) -> dict[str, DataFrame]:
    """One row (estimate, bits of the state) for each method over the part keys.

    The state of a sketch depends on the set of keys alone, that of a sequential counter on the order of first arrivals: both get
    every key once. The exact and built-in counts and the row sample are made from all rows.
    """
    rows = _lineitem(spark, sf).select("l_partkey")
    once = _first_seen(rows, "l_partkey")
    keys = once.select("l_partkey")
    packed = lambda seed: partial.estimates(partial.sketch_by(keys, "l_partkey", seed), seed).select("estimate", (F.col("packed_bytes") * 8).alias("bits"))
    raw = _stored(cells.raw_cells(keys, "l_partkey", PARITY), "cells")  # tables x bins rows at most, read four times
    state = _stored(cells.with_cut(raw, PARITY, BUDGET), "state")
    plain = lambda df, bits: df.select(F.col("estimate").cast("double").alias("estimate"), F.lit(bits).cast("long").alias("bits"))
    rough = lambda mode: by_group(once.withColumn("g", F.lit(0)), "l_partkey", "o", seeding.init(SketchParams(5, 256, 8, budget=4.0), "rough", mode), ["g"]).select("estimate", "bits")
    built = counters.built_in(rows, "l_partkey")
    out = {
        "exact": plain(rows.agg(F.countDistinct("l_partkey").alias("estimate")), 0),
        "single_cut": packed(kwise_seed()),
        "single_cut_independent": packed(seeding.init(KWISE, "b6", "independent")),
        "single_tiny_delta": packed(seeding.init(TINY, "tiny")),
        "nested": packed(nested.nested_seed(NESTED_PARAMS, "nested")),
        "pairwise_bins": cells.estimate(state, PARITY, OFFSET).join(cells.size_bits(state, PARITY)).select("estimate", F.col("cell_bits").alias("bits")),
        "bit_pattern": plain(counters.bit_pattern(keys, "l_partkey", PARITY, ideal=True), 64 * PARITY.b),
        "max_level": plain(counters.max_level(keys, "l_partkey", PARITY), 7 * PARITY.l),
        "binned_levels": plain(counters.binned_levels(keys, "l_partkey", PARITY), 7 * PARITY.l * PARITY.b),
        "rough_tracked": rough("independent"),
        "walk_seeded": rough("walk_16"),
        "sampling": plain(counters.sampling(_lineitem(spark, sf), "l_partkey", 0.1), 0),
    }
    return out | {name: plain(built.select(F.col(name).alias("estimate")), 0) for name in ("hll_plus", "hll_sketch", "theta")}


def baseline_comparison(spark, sf):
    """Every counter on one key: whether it merges, and whether it is within its tolerance."""
    exact = _lineitem(spark, sf).agg(F.countDistinct("l_partkey").alias("exact"))
    found = _all_methods(spark, sf)
    each = [found[name].select(F.lit(name).alias("method"), F.lit(merges).alias("mergeable"), "estimate", F.lit(tolerance).alias("_t")) for name, merges, tolerance in METHODS]
    every = reduce(DataFrame.unionByName, each).join(F.broadcast(exact))
    return every.select("method", "mergeable", "exact", (F.abs(F.col("estimate") - F.col("exact")) <= F.col("_t") * F.col("exact")).alias("within"))


def baseline_bits(spark, sf):
    """Estimate and bits of every counter's state (0 where the engine's own counters don't tell)."""
    found = _all_methods(spark, sf)
    return reduce(DataFrame.unionByName, [found[name].select(F.lit(name).alias("method"), "estimate", "bits") for name, _, _ in METHODS])


def nested_within(spark, sf):
    """The nested sketch for a failure probability of 1e-6: all its copies from one scan."""
    rows = _lineitem(spark, sf).select("l_partkey")
    seed = nested.nested_seed(NESTED_PARAMS, "nested")
    return _within(partial.estimates(partial.sketch_by(rows, "l_partkey", seed), seed), rows.agg(F.countDistinct("l_partkey").alias("exact")), [])


def nested_store_within(spark, sf):
    """Nested sketches by ship year, stored, read with pruning and merged to flags."""
    seed = nested.nested_seed(NESTED_PARAMS, "nested")
    path = shared_folder(spark) + f"/mergecount-nested-{uuid.uuid4().hex}"
    rows = _lineitem(spark, sf).withColumn("year", F.year("l_shipdate"))
    store.write(partial.sketch_by(rows, "l_partkey", seed, ["l_returnflag", "year"]), path, seed, ["year"])
    found = store.rollup(spark, path, seed, ["l_returnflag"], "year >= 1995")
    exact = rows.filter("year >= 1995").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("exact"))
    return _within(found, exact, ["l_returnflag"])


def sketch_store_within(spark, sf):
    """Base sketches by ship year, written, merged into twice (a replay changes nothing), read back with pruning, merged to flags."""
    seed = kwise_seed()
    path = shared_folder(spark) + f"/mergecount-store-{uuid.uuid4().hex}"
    rows = _lineitem(spark, sf).withColumn("year", F.year("l_shipdate"))
    early, late = (partial.sketch_by(rows.filter(c), "l_partkey", seed, ["l_returnflag", "year"]) for c in ("year <= 1996", "year >= 1996"))
    store.write(early, path, seed, ["year"])
    for _ in range(2):
        store.merge_into(late, path, seed, ["l_returnflag", "year"], ["year"])
    found = store.rollup(spark, path, seed, ["l_returnflag"], "year >= 1995")
    exact = rows.filter("year >= 1995").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("exact"))
    return _within(found, exact, ["l_returnflag"])


def packed_cube_within(spark, sf):
    """The cube of the flags from packed base sketches."""
    seed = kwise_seed()
    base = partial.sketch_by(_lineitem(spark, sf), "l_partkey", seed, FLAGS)
    found = partial.estimates(rollup.merged_sketches(base, FLAGS, seed), seed)
    exact = _lineitem(spark, sf).cube(*FLAGS).agg(F.countDistinct("l_partkey").alias("exact"), F.grouping_id().cast("int").alias("gid"))
    on = [found[c].eqNullSafe(exact[c]) for c in [*FLAGS, "gid"]]
    joined = found.join(exact, on)
    return joined.select(*[exact[c] for c in FLAGS], exact["gid"], "exact", (F.abs(F.col("estimate") - F.col("exact")) <= 0.15 * F.col("exact")).alias("within"))


def stored_sets_within(spark, sf):
    """Customers and those with finished orders: overlap, difference and union from two sketches."""
    seed = kwise_seed()
    a = partial.sketch_by(read(spark, sf, "customer"), "c_custkey", seed).withColumnRenamed("sketch", "a")
    b = partial.sketch_by(read(spark, sf, "orders").filter("o_orderstatus = 'F'"), "o_custkey", seed).withColumnRenamed("sketch", "b")
    found = setops.set_estimates(a.join(b), seed)
    exact = setops.exact_overlap(read(spark, sf, "customer"), read(spark, sf, "orders").filter("o_orderstatus = 'F'"), "c_custkey", "o_custkey").withColumnsRenamed({c: f"x_{c}" for c in ("in_both", "only_a", "in_either")})
    near = lambda c: F.abs(F.col(c) - F.col(f"x_{c}")) <= 0.15 * F.col("x_in_either")
    return found.join(exact).select(*[F.col(f"x_{c}").alias(c) for c in ("in_both", "only_a", "in_either")], (near("in_both") & near("only_a") & near("in_either")).alias("within"))


def _digest_within(df: DataFrame, column: str, group: list[str]) -> DataFrame:
    seed = kwise_seed()
    key, _ = key64(df, column)
    keyed = df.select(*group, key.alias("k"))
    return _within(partial.estimates(partial.sketch_by(keyed, "k", seed, group), seed), df.groupBy(*group).agg(F.countDistinct(column).alias("exact")), group)


def texts_by_source_within(spark, sf):
    return _digest_within(read(spark, sf, "documents").select("source", "text"), "text", ["source"])


def urls_within(spark, sf):
    return _digest_within(read(spark, sf, "pages").select("url"), "url", [])


def turns_by_role_within(spark, sf):
    return _digest_within(read(spark, sf, "conversations").select("role", "text"), "text", ["role"])


def conversations_shared_within(spark, sf):
    """Texts of first turns that occur in later turns too: intersection and union of two sketches."""
    seed = kwise_seed()
    turns = read(spark, sf, "conversations").select("turn", "text")
    key, _ = key64(turns, "text")
    sets = [turns.filter(c).select(key.alias("k")) for c in ("turn <= 1", "turn > 1")]
    a, b = (partial.sketch_by(df, "k", seed).withColumnRenamed("sketch", name) for df, name in zip(sets, "ab", strict=True))
    exact = setops.exact_overlap(*sets, "k", "k").select(F.col("in_both").alias("both"), F.col("in_either").alias("either"))
    found = setops.set_estimates(a.join(b), seed).join(exact)
    near = lambda c, x: F.abs(F.col(c) - F.col(x)) <= 0.15 * F.col("either")
    return found.select("both", "either", (near("in_both", "both") & near("in_either", "either")).alias("within"))


def rough_tracked_within(spark, sf):
    """The sequential counters by event type in order of arrival: copies, and seeds from a walk with rough states as differences."""
    out = None
    exact = read(spark, sf, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("exact"))
    for kind, mode in (("copies", "independent"), ("walk", "walk_16")):
        found = by_group(read(spark, sf, "events"), "user_id", "event_id", seeding.init(SketchParams(9, 256, 8, budget=4.0), "rough", mode), ["event_type"])
        one = found.join(exact, "event_type").select(F.lit(kind).alias("seeds"), "event_type", "exact", (F.abs(F.col("estimate") - F.col("exact")) <= 0.5 * F.col("exact")).alias("within"), (F.col("delta_bits") < F.col("bits")).alias("differences_smaller"))
        out = one if out is None else out.unionByName(one)
    return out


# -- many draws on real keys --------------------------------------------------------------------------------------

DRAWS = 200
#: Sizes of the sweep (tables, bins, copies) and the accuracy at which failures are counted.
SWEEP = ((3, 256, 1, 0.3), (9, 256, 1, 0.3), (5, 1024, 1, 0.15), (3, 256, 3, 0.3))
SWEEP_KEYS = (("user_id", "events", "user_id"), ("part", "lineitem", "l_partkey"))


def _draw_seed(config: int, draw: int):
    l, b, m, _ = SWEEP[config]  # noqa: E741
    inner = SketchParams(l, b, 8)
    if m == 1:
        return seeding.init(inner, f"sweep-{config}-{draw}")
    return nested.nested_seed(nested.derive_nested(64, 0.3, 1e-6, inner=inner, m=m), f"sweep-{config}-{draw}")


def _fold_draws(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (which, k): a packed sketch of the task's keys for every key column, size and draw."""
    held: dict[tuple, Sketch | nested.NestedSketch] = {}
    for batch in batches:
        names = np.array(batch.column(0).to_pylist())
        keys = np.asarray(batch.column(1).to_numpy()).astype(np.int64).view(np.uint64)
        for which in np.unique(names):
            for config in range(len(SWEEP)):
                for draw in range(DRAWS):
                    key = (str(which), config, draw)
                    if key not in held:
                        held[key] = partial._empty(_draw_seed(config, draw))
                    held[key].update(keys[names == which])
    for (which, config, draw), one in held.items():
        yield pa.RecordBatch.from_arrays([pa.array([which]), pa.array([config], pa.int32()), pa.array([draw], pa.int32()), pa.array([one.pack("bytes")], pa.binary())], names=["which", "config", "draw", "sketch"])


def _merge_draws(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (which, config, draw, sketch) sorted: one estimate for each run; one sketch is held."""
    now, held = None, None

    def done() -> pa.RecordBatch:
        e = partial._estimate(held)
        return pa.RecordBatch.from_arrays([pa.array([now[0]]), pa.array([now[1]], pa.int32()), pa.array([now[2]], pa.int32()), pa.array([float(e.value)]), pa.array([int(e.q)], pa.int32())], names=["which", "config", "draw", "estimate", "q"])

    for batch in batches:
        for which, config, draw, blob in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            one = partial._unpack(_draw_seed(config, draw), blob)
            if (which, config, draw) == now:
                held = held.merge(one)
                continue
            if held is not None:
                yield done()
            now, held = (which, config, draw), one
    if held is not None:
        yield done()


def accuracy_sweep(spark, sf):
    """Failure rates over many draws on real keys, for growing tables, bins and copies: a task sends one blob for each draw."""
    keys = reduce(DataFrame.union, [read(spark, sf, t).select(F.lit(name).alias("which"), F.col(c).cast("long").alias("k")).filter("k is not null").distinct() for name, t, c in SWEEP_KEYS])
    names = ["which", "config", "draw"]
    blobs = keys.mapInArrow(_fold_draws, "which string, config int, draw int, sketch binary")
    found = blobs.repartition(*names).sortWithinPartitions(*names).mapInArrow(_merge_draws, "which string, config int, draw int, estimate double, q int")
    exact = keys.groupBy("which").agg(F.count("*").alias("exact"))
    eps = F.element_at(F.array(*[F.lit(x[3]) for x in SWEEP]), F.col("config") + 1)
    error = F.abs(F.col("estimate") / F.col("exact") - 1)
    return found.join(exact, "which").groupBy("which", "config", "exact").agg(F.count("*").alias("draws"), F.sum((error > eps).cast("int")).alias("failures"), F.round(F.sqrt(F.avg(error * error)), 4).alias("rms"), F.max("q").alias("q"))


def accuracy_sweep_within(spark, sf):
    """Of the sweep: whether at most 5 % of the draws fail, and the root mean square error keeps below the accuracy."""
    eps = F.element_at(F.array(*[F.lit(x[3]) for x in SWEEP]), F.col("config") + 1)
    return accuracy_sweep(spark, sf).select("which", "config", "exact", "draws", ((F.col("failures") <= 0.05 * F.col("draws")) & (F.col("rms") <= eps / 2)).alias("within"))


# -- walks on an explicit graph -------------------------------------------------------------------------------------


def _steps(side: int, half: int, v: np.ndarray, e: np.ndarray) -> np.ndarray:
    """One step of the base graph for arrays of vertices and edges."""
    m = side - 1
    x, y, sign, shear = v & m, v >> half, np.where(e < 4, 1, -1), e % 4
    extra = shear & 1
    new_y = np.where(shear < 2, (y + sign * (2 * x + extra)) & m, y)
    new_x = np.where(shear < 2, x, (x + sign * (2 * y + extra)) & m)
    return new_x | new_y << half


def walk_visits(spark: SparkSession, values: DataFrame, minus_log_lambda: float, walks: int, length: int) -> DataFrame:
    """(walk, place, value): the values (v, value) that random walks on the explicit graph meet; vertices are numbered from 0 and padded to the graph.

    Walks are drawn where their rows are; their vertices meet the values by a join, whatever the number of vertices.
    """
    n = max(2, values.count())
    graph = Graph((n - 1).bit_length(), minus_log_lambda)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = np.asarray(batch.column(0).to_numpy())
            rng = np.random.default_rng([11, int(ids[0]) if len(ids) else 0, length])
            v = rng.integers(0, 1 << graph.bits, len(ids))
            out = [v]
            for _ in range(length - 1):
                for _ in range(graph.steps):
                    v = _steps(graph.side, graph.bits // 2, v, rng.integers(0, 8, len(ids)))
                out.append(v)
            yield pa.RecordBatch.from_arrays([pa.array(np.tile(ids, length)), pa.array(np.repeat(np.arange(length), len(ids)).astype(np.int32)), pa.array(np.concatenate(out))], names=["walk", "place", "v"])

    drawn = spark.range(0, walks, 1, 8).mapInArrow(run, "walk long, place int, v long")
    return drawn.join(values, "v", "left").select("walk", "place", F.coalesce("value", F.lit(0.0)).alias("value"))


def _numbered(df: DataFrame, key: str, value) -> DataFrame:
    """(v, value): keys that run from 1 as vertices from 0."""
    return df.select((F.col(key) - 1).cast("long").alias("v"), value.cast("double").alias("value"))


def walk_tail(spark, sf):
    """Walks over all customers: how often a share of the places is in a set, or all first places are, beside the bounds; also the tail that the copies' median has."""
    lam, g = WALK_LAMBDA, 0.5
    out = None
    for name, segment in (("segment", "BUILDING"), ("rare", None)):
        value = (F.col("c_mktsegment") == segment) if segment else (F.col("c_custkey") % 16 == 1)
        values = _numbered(read(spark, sf, "customer"), "c_custkey", value)
        padded = 1 << (lambda bits: bits + bits % 2)((max(2, values.count()) - 1).bit_length())
        mu = values.agg(F.sum("value")).first()[0] / padded
        for length in WALK_LENGTHS:
            seen = walk_visits(spark, values, -math.log(lam), WALKS, length).groupBy("walk").agg(F.avg("value").alias("share"), F.min(F.when(F.col("place") < 3, F.col("value"))).alias("all_first"))
            one = seen.agg(F.avg((F.col("share") >= g).cast("double")).alias("observed"), F.avg("all_first").alias("hit"))
            tail, hitting = bounds.tail_kl(mu, lam, g, length), bounds.hitting(mu, lam, 3)[0]
            slack = lambda p: 4 * math.sqrt(p * (1 - p) / WALKS) + 1 / WALKS
            one = one.select(F.lit(name).alias("set_name"), F.lit(length).alias("length"), (F.col("observed") <= tail + slack(min(1.0, tail))).alias("tail_ok"), (F.col("hit") <= hitting + slack(hitting)).alias("hitting_ok"))
            out = one if out is None else out.unionByName(one)
    return out


def deviation_walk(spark, sf):
    """Walks over all parts with an unbounded function whose tail is exp(-x ln(x)^3): sums reach the constant times the length as rarely as the bound says."""
    part = read(spark, sf, "part")
    # The chance that a uniform u is below exp(-x ln(x)^3) gives the function its tail; u from the part's size and key.
    u = (F.pmod(F.xxhash64("p_partkey", "p_size"), F.lit(1 << 30)) + 1) / F.lit(float(1 << 30))
    rungs = F.array(*[F.lit(x / 4) for x in range(4, 81)])
    value = F.aggregate(rungs, F.lit(1.0), lambda acc, x: F.when(u <= F.exp(-x * F.pow(F.log(x), 3)), x).otherwise(acc))
    values = _numbered(part, "p_partkey", value)
    out = None
    for length in (4, 8):
        lam = max(math.log(16), length * math.log(length) ** 3)
        sums = walk_visits(spark, values, lam, WALKS, length).groupBy("walk").agg(F.sum("value").alias("total"))
        one = sums.agg(F.avg((F.col("total") >= bounds.C_DEV * length).cast("double")).alias("observed"), F.max("total").alias("_most"))
        one = one.select(F.lit(length).alias("length"), F.lit(round(bounds.deviation(length), 9)).alias("bound"), (F.col("observed") <= bounds.deviation(length) + 1 / WALKS).alias("within"), (F.col("_most") > length).alias("unbounded"))
        out = one if out is None else out.unionByName(one)
    return out


# -- streams ----------------------------------------------------------------------------------------------------------


def _replayed(spark: SparkSession, sf: str, base: str) -> DataFrame:
    """The events as a stream of three files."""
    read(spark, sf, "events").select("ts", "user_id", "event_type").repartition(3).write.parquet(f"{base}/in")
    return spark.readStream.schema(spark.read.parquet(f"{base}/in").schema).option("maxFilesPerTrigger", 1).parquet(f"{base}/in")


def sliding_stream_within(spark, sf):
    """Users of two days, every day, from a stream of cells."""
    base = shared_folder(spark) + f"/mergecount-stream-{uuid.uuid4().hex}"
    state = windows.window_cells(_replayed(spark, sf, base), "ts", "user_id", PARITY, "2 days", "1 day", late="40 days")
    windows.start(state, PARITY, f"{base}/checkpoint", lambda batch, no: batch.write.mode("overwrite").parquet(f"{base}/out/batch={no}")).awaitTermination()
    merged = spark.read.parquet(f"{base}/out").groupBy("window", "tab", "bin").agg(F.max("level").alias("level"))
    found = windows.window_estimates(merged, PARITY, BUDGET, OFFSET).select(F.col("window_start").cast("string").alias("day"), "estimate")
    exact = read(spark, sf, "events").groupBy(F.window("ts", "2 days", "1 day")).agg(F.countDistinct("user_id").alias("exact")).select(F.col("window.start").cast("string").alias("day"), "exact")
    return found.join(exact, "day").select("day", "exact", (F.abs(F.col("estimate") - F.col("exact")) <= 0.5 * F.col("exact")).alias("within"))


def packed_stream_within(spark, sf):
    """Users of each day from a stream whose state is one packed sketch a day."""
    base, seed = shared_folder(spark) + f"/mergecount-stream-{uuid.uuid4().hex}", kwise_seed()
    state = windows.packed_stream(_replayed(spark, sf, base), "ts", "user_id", seed, "1 day")
    state.writeStream.outputMode("update").option("checkpointLocation", f"{base}/checkpoint").foreachBatch(lambda batch, no: batch.write.mode("overwrite").parquet(f"{base}/out/batch={no}")).trigger(availableNow=True).start().awaitTermination()
    changed = spark.read.parquet(f"{base}/out").select("window_start", "sketch")
    found = partial.estimates(partial.merge_by(changed, seed, ["window_start"]), seed).select(F.timestamp_seconds("window_start").cast("string").alias("day"), "estimate")
    exact = read(spark, sf, "events").groupBy(F.window("ts", "1 day")).agg(F.countDistinct("user_id").alias("exact")).select(F.col("window.start").cast("string").alias("day"), "exact")
    return _within(found, exact, ["day"])


def session_stream(spark, sf):
    """Sessions of each event type (a gap of two hours ends one) from a stream: their number and users, exact while they are few."""
    base = shared_folder(spark) + f"/mergecount-stream-{uuid.uuid4().hex}"
    rows = _replayed(spark, sf, base).repartition(spark.sparkContext.defaultParallelism)  # one file a batch, but all cores make its cells
    state = windows.session_cells(rows, "ts", "user_id", PARITY, "2 hours", ["event_type"], late="40 days")

    def sink(batch: DataFrame, no: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/out/batch={no}")

    with windows.sessions_merged_early(spark):
        query = state.writeStream.outputMode("complete").option("checkpointLocation", f"{base}/checkpoint").foreachBatch(sink).trigger(availableNow=True).start()
    query.awaitTermination()
    rows = spark.read.parquet(f"{base}/out")
    last = rows.filter(F.col("batch") == rows.agg(F.max("batch")).first()[0])
    return last.groupBy("event_type").agg(F.countDistinct("window").alias("sessions"))


def dedup_stream_exact(spark, sf):
    """Exact yardstick of a stream: repeats of a user within a day and the watermark are dropped, the rest is counted."""
    base = shared_folder(spark) + f"/mergecount-stream-{uuid.uuid4().hex}"
    rows = _replayed(spark, sf, base).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "40 days").withColumn("day", F.date_trunc("day", "ts"))
    unique = rows.dropDuplicatesWithinWatermark(["day", "user_id"]).select("day", "user_id")
    unique.writeStream.outputMode("append").option("checkpointLocation", f"{base}/checkpoint").trigger(availableNow=True).format("parquet").option("path", f"{base}/out").start().awaitTermination()
    return spark.read.parquet(f"{base}/out").groupBy(F.col("day").cast("string").alias("day")).agg(F.count("*").alias("users"))


def late_rows_stream(spark, sf):
    """Rows that come after the watermark has passed their day are left out; others count, whatever their order."""
    base = shared_folder(spark) + f"/mergecount-stream-{uuid.uuid4().hex}"
    day = lambda d: F.timestamp_seconds(F.lit(1_704_067_200 + 86_400 * d))
    for no, (d, first) in enumerate(((0, 0), (9, 100), (0, 200))):  # a day, a later one that moves the watermark, the first again
        spark.range(first, first + 50, 1, 1).select(day(d).alias("ts"), F.col("id").alias("user_id")).write.parquet(f"{base}/in/{no}")
    schema = spark.read.parquet(f"{base}/in/0").schema
    seen = []
    for no in range(3):
        source = spark.readStream.schema(schema).parquet(f"{base}/in/[0-{no}]")
        state = windows.window_cells(source, "ts", "user_id", PARITY, "1 day", late="2 days")
        windows.start(state, PARITY, f"{base}/checkpoint", lambda batch, k, no=no: batch.write.mode("overwrite").parquet(f"{base}/out/batch={no}-{k}")).awaitTermination()
        seen.append(no)
    merged = spark.read.parquet(f"{base}/out").groupBy("window", "tab", "bin").agg(F.max("level").alias("level"))
    known = cells.raw_cells(spark.range(50).withColumn("window", F.lit(1)), "id", PARITY, ["window"])
    first = merged.filter(F.col("window.start") == day(0)).select("tab", "bin", "level")
    return first.agg(F.count("*").alias("cells")).join(known.agg(F.count("*").alias("cells_of_rows_in_time"))).select((F.col("cells") == F.col("cells_of_rows_in_time")).alias("late_rows_left_out"))


QUERIES = (
    cardinality_sweep, cut_margin_sweep, column_space, operation_counts, level_tails, event_frequencies, balls_thrown, cost_drops, cut_forms_agree, estimate_at_any_cut, cut_sharing_ablation,
    communication_measured, seed_report, form_choice, tail_bounds_more, inverse_tables, asof_purchase_view, distinct_in_ranges, baseline_comparison, baseline_bits, nested_within, nested_store_within, sketch_store_within,
    packed_cube_within, stored_sets_within, texts_by_source_within, urls_within, turns_by_role_within, conversations_shared_within, rough_tracked_within, accuracy_sweep, accuracy_sweep_within,
    walk_tail, deviation_walk, sliding_stream_within, packed_stream_within, session_stream, dedup_stream_exact, late_rows_stream,
)
