"""Distinct counts over event time: sketch cells as streaming state, cut and estimated per trigger.

The state of a window is the largest level of each cell, an aggregate that Spark keeps in its own
state store; replays and late rows merge without harm. Estimates are made from a batch of changed
windows, or from stored packed sketches that are merged to longer windows.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.native import NativeSeed, levels_and_bins
from ..functions.seeding import Seed
from ..operators import cells


def _watermarked(events: DataFrame, time: str, late: str | None) -> DataFrame:
    """With a watermark, if asked for; it needs a timestamp with a zone."""
    return events.withColumn(time, F.col(time).cast("timestamp")).withWatermark(time, late) if late else events


def window_cells(events: DataFrame, time: str, key: str, seed: NativeSeed, length: str, slide: str | None = None, late: str | None = None) -> DataFrame:
    """Cells (window, tab, bin, level) of tumbling or sliding windows; batch or streaming."""
    rows = _watermarked(events, time, late)
    levels = levels_and_bins(rows, key, seed, [time])
    return levels.groupBy(F.window(time, length, slide) if slide else F.window(time, length), "tab", "bin").agg(F.max("level").alias("level"))


def session_cells(events: DataFrame, time: str, key: str, seed: NativeSeed, gap: str, by: list[str], late: str | None = None) -> DataFrame:
    """Cells (window, by..., tab, bin, level) per session of the columns ``by``; batch or streaming.

    A session keeps the set of its cells' levels, at most tables x bins x levels entries however many keys it has.
    """
    rows = _watermarked(events, time, late)
    levels = levels_and_bins(rows, key, seed, [time, *by])
    sessions = levels.groupBy(F.session_window(time, gap), *by).agg(F.collect_set(F.struct("tab", "bin", "level")).alias("_cells"))
    top = lambda own: F.filter(own, lambda x, i: F.coalesce((F.get(own, i + 1)["tab"] != x["tab"]) | (F.get(own, i + 1)["bin"] != x["bin"]), F.lit(True)))
    # sorted by table, bin and level: a cell's last entry is its largest; a lambda's variable, so that the sort is done once and not for every entry
    last = F.get(F.transform(F.array(F.sort_array("_cells")), top), F.lit(0))
    one = sessions.select(F.col("session_window").alias("window"), *by, F.explode(last).alias("_c"))
    return one.select("window", *by, "_c.tab", "_c.bin", "_c.level")


@contextmanager
def sessions_merged_early(spark: SparkSession) -> Iterator[None]:
    """Queries that are started inside merge a task's sessions before they are dealt by the columns ``by``.

    Without it every cell of every row goes to the one task that has its group. A query keeps the setting that it started with.
    """
    name = "spark.sql.streaming.sessionWindow.merge.sessions.in.local.partition"
    was = spark.conf.get(name)
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        spark.conf.set(name, was)


def window_estimates(state: DataFrame, seed: NativeSeed, budget: float, offset: int) -> DataFrame:
    """(window_start, window_end, estimate, q) of a batch of cells."""
    flat = state.select(F.col("window.start").alias("window_start"), F.col("window.end").alias("window_end"), "tab", "bin", "level")
    group = ["window_start", "window_end"]
    return cells.estimate(cells.with_cut(flat, seed, budget, group), seed, offset, group)


def start(state: DataFrame, seed: NativeSeed, checkpoint: str, sink: Callable[[DataFrame, int], None], trigger: dict | None = None):
    """Starts a streaming query that hands each trigger's changed windows (as cells) to ``sink`` in update mode."""
    writer = state.writeStream.outputMode("update").option("checkpointLocation", checkpoint).foreachBatch(sink)
    return writer.trigger(**(trigger or {"availableNow": True})).start()


def longer_windows(state: DataFrame, length: str) -> DataFrame:
    """Cells of longer tumbling windows by merging those of shorter ones that lie in them."""
    return state.groupBy(F.window("window.start", length).alias("window"), "tab", "bin").agg(F.max("level").alias("level"))


def packed_stream(events: DataFrame, time: str, key: str, seed: Seed, length: str) -> DataFrame:
    """(window_start, sketch) of windows that a trigger changes, update mode: the state of a window is one packed sketch.

    The state has a fixed size whatever the window's keys; it is kept for late rows as long as the query runs.
    """
    keyed = events.filter(F.col(key).isNotNull()).select(F.window(time, length)["start"].cast("timestamp").cast("long").alias("_start"), F.col(key).cast("long").alias("_key"))

    def update(name: tuple, parts: Iterator, state) -> Iterator:
        import pandas as pd

        from ..sketch import Context, Sketch

        context = Context.of(seed)
        sketch = Sketch.unpack(context, bytes(state.get[0])) if state.exists else Sketch(context)
        for part in parts:
            sketch.update(part["_key"].to_numpy().astype("int64").view("uint64"))
        state.update((sketch.pack(),))
        yield pd.DataFrame({"window_start": [name[0]], "sketch": [sketch.pack()]})

    return keyed.groupBy("_start").applyInPandasWithState(update, "window_start long, sketch binary", "sketch binary", "update", "NoTimeout")


def exact_stream(events: DataFrame, time: str, key: str, length: str, late: str) -> DataFrame:
    """Exact yardstick: rows that repeat a key within the watermark and window are dropped, the rest is counted."""
    rows = _watermarked(events, time, late).withColumn("window", F.window(time, length))
    return rows.dropDuplicates(["window", key]).groupBy("window").agg(F.count("*").alias("distinct"))
