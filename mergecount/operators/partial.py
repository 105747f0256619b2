"""Packed sketches: folded in Arrow batches, merged in two levels; the form for large inputs.

A task holds one l x b byte matrix per group it meets and sends one packed row for each, so what is
shuffled is (tasks x groups) small blobs, not cells. Groups beyond ``HELD`` are sent early and
merge later: the state is history independent. A hot group's blobs are merged by salt first. A nested
seed makes nested sketches: all copies from one scan, in one blob.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.seeding import Seed
from ..nested import NestedSeed, NestedSketch
from ..sketch import Context, Estimate, Sketch

#: Bytes of matrices that a task holds before it sends what it has.
HELD = 256 << 20
#: Rows that a task gathers before it hashes their distinct keys.
BUFFER = 1 << 17


def _fields(df: DataFrame, group: list[str]) -> list[T.StructField]:
    return [df.schema[c] for c in group]


AnySeed = Seed | NestedSeed


def _contexts(seed: AnySeed) -> list[Context]:
    return [p.context for p in NestedSketch(seed.params, seed.seeds).parts] if isinstance(seed, NestedSeed) else [Context.of(seed)]


def _empty(seed: AnySeed) -> Sketch | NestedSketch:
    return NestedSketch(seed.params, seed.seeds) if isinstance(seed, NestedSeed) else Sketch(Context.of(seed))


def _unpack(seed: AnySeed, blob: bytes) -> Sketch | NestedSketch:
    return NestedSketch.unpack(seed, blob) if isinstance(seed, NestedSeed) else Sketch.unpack(Context.of(seed), blob)


def _parts(sketch: Sketch | NestedSketch) -> list[Sketch]:
    return sketch.parts if isinstance(sketch, NestedSketch) else [sketch]


def _size(seed: AnySeed) -> int:
    """Bytes of a sketch's levels."""
    p = seed.params.inner if isinstance(seed, NestedSeed) else seed.params
    return p.l * p.b * (seed.params.m if isinstance(seed, NestedSeed) else 1)


def _fresh(seed: AnySeed, keys: np.ndarray, group: np.ndarray, before: list) -> list:
    """Sketches of the keys of each group; a key is hashed once, however many groups and rows have it.

    Levels below every group's cut are left out: they could only make cells that the cut empties.
    """
    unique, back = np.unique(keys, return_inverse=True)
    found = []  # by copy, then by group
    for c, context in enumerate(_contexts(seed)):
        p = context.params
        floor = min(0 if s is None else _parts(s)[c].q for s in before)
        levels = np.full((len(before), p.l, p.b), -1, dtype=np.int8)
        for t, triple in enumerate(context.triples):
            level = triple.level.many(unique)
            kept = level >= floor
            bins = np.zeros(len(unique), dtype=np.intp)
            bins[kept] = triple.bins.many(unique[kept])
            rows = kept[back]
            own = back[rows]
            np.maximum.at(levels[:, t, :], (group[rows], bins[own]), level[own].astype(np.int8))
        found.append([Sketch(context, x).compress() for x in levels])
    if isinstance(seed, NestedSeed):
        return [NestedSketch(seed.params, seed.seeds, list(parts)) for parts in zip(*found, strict=True)]
    return found[0]


def _fold(seed: AnySeed, width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        room = max(1, HELD // _size(seed))
        held: dict[tuple, Sketch | NestedSketch] = {}
        schema = None

        def send() -> pa.RecordBatch:
            keys, blobs = list(held), [s.pack("deflate") for s in held.values()]
            columns = [pa.array([k[i] for k in keys], schema.field(i).type) for i in range(width)]
            held.clear()
            return pa.RecordBatch.from_arrays([*columns, pa.array(blobs, pa.binary())], names=[*schema.names[:width], "sketch"])

        def absorb(parts: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            table = pa.Table.from_batches(parts)
            keys = np.asarray(table.column(width).to_numpy()).astype(np.int64).view(np.uint64)
            if not width:
                held.setdefault((), _empty(seed)).update(keys)
                return
            numbered = table.append_column("_row", pa.array(np.arange(table.num_rows)))
            groups = numbered.group_by(schema.names[:width]).aggregate([("_row", "list")])
            names = list(zip(*[groups.column(n).to_pylist() for n in schema.names[:width]], strict=True))
            lists = groups.column("_row_list").combine_chunks()
            rows = lists.flatten().to_numpy()
            group = np.repeat(np.arange(len(names)), lists.value_lengths().to_numpy())
            for at in range(0, len(names), room):
                own = names[at : at + room]
                inside = (group >= at) & (group < at + room)
                for key, fresh in zip(own, _fresh(seed, keys[rows[inside]], group[inside] - at, [held.get(k) for k in own]), strict=True):
                    held[key] = held[key].merge(fresh) if key in held else fresh
                if len(held) >= room:
                    yield send()

        waiting: list[pa.RecordBatch] = []
        for batch in batches:
            schema = batch.schema
            waiting.append(batch)
            if sum(x.num_rows for x in waiting) >= BUFFER:
                yield from absorb(waiting)
                waiting = []
        if waiting:
            yield from absorb(waiting)
        if held:
            yield send()

    return run


def sketch_by(df: DataFrame, key: str, seed: AnySeed, group: list[str] = ()) -> DataFrame:
    """(group..., sketch binary), one row for each group: distinct keys of ``df``, read once; null keys are left out."""
    group = list(group)
    rows = df.filter(F.col(key).isNotNull()).select(*group, F.col(key).cast("long").alias("_key"))
    schema = T.StructType([*_fields(df, group), T.StructField("sketch", T.BinaryType())])
    return merge_by(rows.mapInArrow(_fold(seed, len(group)), schema), seed, group)


def _merge_runs(seed: AnySeed, width: int, codec: str):
    """Rows (keys..., sketch) sorted by the keys: one row for each run, merged as it passes; one sketch is held."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held, schema = None, None, None

        def done() -> pa.RecordBatch:
            columns = [pa.array([v], schema.field(i).type) for i, v in enumerate(now)]
            return pa.RecordBatch.from_arrays([*columns, pa.array([held.pack(codec)], pa.binary())], names=[*schema.names[:width], "sketch"])

        for batch in batches:
            schema = batch.schema
            for i in range(batch.num_rows):
                key = tuple(batch.column(c)[i].as_py() for c in range(width))
                one = _unpack(seed, batch.column(width)[i].as_py())
                if key == now and held is not None:
                    held = held.merge(one)
                    continue
                if held is not None:
                    yield done()
                now, held = key, one
        if held is not None:
            yield done()

    return run


def merge_by(sketches: DataFrame, seed: AnySeed, group: list[str] = ()) -> DataFrame:
    """Merges the ``sketch`` column per group, in two levels.

    A group's blobs are dealt to as many parts as a shuffle has (so one group's blobs keep all tasks
    busy), merged part by part, then the parts' results; every merge streams and holds one sketch.
    """
    group = list(group)
    parts = int(sketches.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def level(df: DataFrame, keys: list[str], codec: str) -> DataFrame:
        schema = T.StructType([*[df.schema[k] for k in keys], T.StructField("sketch", T.BinaryType())])
        dealt = df.select(*keys, "sketch").repartition(*keys).sortWithinPartitions(*keys) if keys else df.select("sketch").repartition(1)
        return dealt.mapInArrow(_merge_runs(seed, len(keys), codec), schema)

    salted = sketches.select(*group, F.pmod(F.xxhash64("sketch"), F.lit(parts)).cast("int").alias("_salt"), "sketch")
    return level(level(salted, [*group, "_salt"], "deflate").select(*group, "sketch"), group, "gamma")


def _estimate(sketch: Sketch | NestedSketch) -> Estimate:
    """Of a nested sketch the median of the copies, the largest cut, and whether any copy is saturated or cut too far."""
    if isinstance(sketch, Sketch):
        return sketch.estimate()
    found = [p.estimate() for p in sketch.parts]
    middle = sorted(found, key=lambda e: e.value)[len(found) // 2]
    return replace(middle, value=sketch.estimate(), q=max(e.q for e in found), saturated=any(e.saturated for e in found), cut_ok=all(e.cut_ok for e in found))


def estimates(sketches: DataFrame, seed: AnySeed) -> DataFrame:
    """Adds estimate, q, saturated and cut_ok to rows with a ``sketch`` column."""
    schema = T.StructType([f for f in sketches.schema.fields if f.name != "sketch"] + [T.StructField("estimate", T.DoubleType()), T.StructField("q", T.IntegerType()), T.StructField("saturated", T.BooleanType()), T.StructField("cut_ok", T.BooleanType()), T.StructField("packed_bytes", T.LongType()), T.StructField("profile", T.StringType())])
    others = [c for c in sketches.columns if c != "sketch"]
    profile = (seed.params.inner if isinstance(seed, NestedSeed) else seed.params).profile

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            blobs = [x.as_py() for x in batch.column(batch.schema.get_field_index("sketch"))]
            found = [_estimate(_unpack(seed, x)) for x in blobs]
            kept = [batch.column(batch.schema.get_field_index(c)) for c in others]
            values = [pa.array([e.value for e in found], pa.float64()), pa.array([e.q for e in found], pa.int32()), pa.array([e.saturated for e in found], pa.bool_()), pa.array([e.cut_ok for e in found], pa.bool_()), pa.array(list(map(len, blobs)), pa.int64()), pa.array([profile] * len(found), pa.string())]
            yield pa.RecordBatch.from_arrays([*kept, *values], names=[f.name for f in schema.fields])

    return sketches.mapInArrow(run, schema)
