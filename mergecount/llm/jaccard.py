"""Near-duplicates by Jaccard similarity of word shingles: SimHash anchors, then an exact check.

A text is the set of its hashed 5-word shingles (ASCII lower case). Texts of one set are one class.
Each class has a SimHash print that goes to one anchor for each of its blocks, and classes of one anchor whose
prints are near are a crowd with a key (``anchors``: at similarity 0.8 two classes meet in one with probability 0.9999 or more).
Classes that share a key are candidates, and a link is one whose sets, computed anew from the texts, have a similarity of at least the asked one.

Candidates are compared in two turns. First each class with the next one of its key, in class order:
rows are dealt by ranges of (key, class), so a key that a third of all classes have is spread over
many tasks, and links of neighbours join a large group without comparing all its pairs. Then the connected
parts that neighbours of a key lie in: those that share keys, directly or over others, are one group, in
which a class stands once, however many keys it has, and all pairs of a group that are not connected yet are compared.
A group of over ``CELL`` classes or ``CELL_BYTES`` of sets is cut in chunks, by size and by the connected parts that are as large,
and only chunks that can have a link are compared: sizes must be in reach of the similarity, and two chunks of one connected
part have none to find. A cell is such a pair of chunks; its intersections are products of its membership matrix.
No candidate is left out: one not compared is connected already, or its sizes alone forbid a link. What grows with the square
of a group is the number of its unconnected classes of like size, over ``CELL``.

Edge cases: null, empty and blank texts are one class; texts with fewer words than a shingle have one
shingle; very long texts are hashed in pieces; an empty table gives an empty result; repeated rows are copies.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import anchors
from . import common as C
from .components import connected_components, with_component

#: Classes and bytes of their sets on a side of a cell of all pairs.
CELL, CELL_BYTES = 256, 8 << 20
_COLUMNS = 1 << 13
_LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
_BASE, _M1, _M2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def shingle_set(text: bytes | None, shingle: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the shingles of a UTF-8 text."""
    import xxhash

    words = (text or b"").translate(_LOWER).split()
    if not words:
        return np.zeros(0, dtype=np.uint64)
    digest = xxhash.xxh64_intdigest
    each = np.fromiter((digest(w) for w in words), np.uint64, len(words))
    size = min(shingle, len(each))
    out = np.full(len(each) - size + 1, np.uint64(size))
    for j in range(size):
        out = out * _BASE + each[j : len(each) - size + 1 + j]
        out ^= out >> np.uint64(29)
    out = (out ^ (out >> np.uint64(30))) * _M1
    out = (out ^ (out >> np.uint64(27))) * _M2
    return np.unique(out ^ (out >> np.uint64(31)))


def similarity_of(a: np.ndarray, b: np.ndarray) -> float:
    if not len(a) or not len(b):
        return float(len(a) == len(b))
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / (len(a) + len(b) - both)


def band_keys(own: np.ndarray) -> list[int]:
    """The anchors of a set: one for each block of its print."""
    return anchors.anchors_of(anchors.prints_of(own)).ravel().tolist()


def _classes(shingle: int) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                part = batch.slice(at, 1024)
                sets = [shingle_set(t.as_py(), shingle) for t in part.column(1)]
                fp = np.array([xxhash.xxh64_intdigest(s.tobytes()) for s in sets], dtype=np.uint64).view(np.int64)
                prints = pa.array([anchors.prints_of(s).tobytes() for s in sets], pa.binary())
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(fp), prints, *part.columns[2:]], names=["doc_id", "fp", "print", "_slot", "_row"])

    return run


def _neighbours(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (key, fp) sorted: (part, key, a, b) for consecutive rows of a key (part null), and the task's first and last row."""
    part, first, last = TaskContext.get().partitionId(), None, None
    make = lambda p, k, a, b: pa.RecordBatch.from_arrays([pa.array(p, pa.int32()), *(pa.array(x, pa.int64()) for x in (k, a, b))], names=["part", "key", "a", "b"])
    for batch in batches:
        key, fp = (np.asarray(c.to_numpy(zero_copy_only=False), dtype=np.int64) for c in batch.columns)
        if not len(key):
            continue
        if first is None:
            first = (key[0], fp[0])
        else:
            key, fp = np.append(last[0], key), np.append(last[1], fp)
        last = (key[-1], fp[-1])
        at = np.flatnonzero((key[1:] == key[:-1]) & (fp[1:] != fp[:-1]))
        yield make([None] * len(at), key[at], fp[at], fp[at + 1])
    if first is not None:
        yield make([part] * 2, [first[0], last[0]], [first[1], last[1]], [0, 1])


def _verify(shingle: int, similarity: float) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            held: dict[int, np.ndarray] = {}
            good = []
            for a, b, x, y in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), batch.column(3), strict=True):
                sets = []
                for fp, text in ((a, x), (b, y)):
                    if fp not in held:
                        if len(held) > 256:
                            held.clear()
                        held[fp] = shingle_set(text.as_py(), shingle)
                    sets.append(held[fp])
                good.append(similarity_of(*sets) >= similarity)
            yield batch.select([0, 1]).filter(pa.array(good, pa.bool_()))

    return run


def overlaps(sets: list[np.ndarray]) -> np.ndarray:
    """Sizes of the intersections of all pairs of sets, by products of their membership in the members that any two share."""
    sizes = [len(x) for x in sets]
    member, count = np.unique(np.concatenate(sets), return_counts=True)
    shared = member[count > 1]
    row = np.repeat(np.arange(len(sets)), sizes)
    place = np.searchsorted(shared, np.concatenate(sets))
    kept = (place < len(shared)) & (shared[np.minimum(place, max(0, len(shared) - 1))] == np.concatenate(sets)) if len(shared) else np.zeros(len(row), dtype=bool)
    row, place = row[kept], place[kept]
    out = np.zeros((len(sets), len(sets)), dtype=np.float64)
    for at in range(0, len(shared), _COLUMNS):  # so many members at once
        own = (place >= at) & (place < at + _COLUMNS)
        part = np.zeros((len(sets), min(_COLUMNS, len(shared) - at)), dtype=np.float32)
        part[row[own], place[own] - at] = 1
        out += part @ part.T
    return out


def _sets(shingle: int) -> Callable:
    """Rows (fp, root, group, text): (fp, root, group, size, set)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                sets = [shingle_set(t.as_py(), shingle) for t in part.column(3)]
                own = [pa.array([len(x) for x in sets], pa.int64()), pa.array([x.tobytes() for x in sets], pa.binary())]
                yield pa.RecordBatch.from_arrays([*part.columns[:3], *own], names=["fp", "root", "group", "size", "set"])

    return run


def _compare_cells(similarity: float) -> Callable:
    """Rows (group, i, j, side, fp, root, set) sorted by cell: links between members of different roots."""

    def found(cell: list[tuple]) -> list[tuple[int, int]]:
        sets = [np.frombuffer(r[6], dtype=np.uint64) for r in cell]
        sizes, side = np.array([len(x) for x in sets], dtype=np.float64), np.array([r[3] for r in cell])
        roots = np.array([r[5] for r in cell], dtype=np.int64)
        both = overlaps(sets)
        either = sizes[:, None] + sizes[None, :] - both
        near = np.where(either > 0, both / np.maximum(either, 1) >= similarity, True) & (roots[:, None] != roots[None, :])
        if cell[0][1] != cell[0][2]:
            near &= side[:, None] != side[None, :]  # one side's own pairs have their own cell
        top = {int(r): int(r) for r in roots}

        def find_root(x: int) -> int:
            while top[x] != x:
                x = top[x]
            return x

        out = []
        for x, y in np.argwhere(np.triu(near, 1)):
            p, q = find_root(int(roots[x])), find_root(int(roots[y]))
            if p != q:
                top[p] = q
                out.append((cell[x][4], cell[y][4]))
        return out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cell: list[tuple] = []
        for batch in batches:
            out = []
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if cell and row[:3] != cell[0][:3]:
                    out += found(cell)
                    cell = []
                cell.append(row)
            yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in out], pa.int64()) for k in (0, 1)], names=["a", "b"])
        if len(cell) > 1:
            out = found(cell)
            yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in out], pa.int64()) for k in (0, 1)], names=["a", "b"])

    return run


def cells(sets: DataFrame, similarity: float) -> DataFrame:
    """(group, i, j, side, fp, root, set): the cells (group, i, j) in which all pairs of a group meet that can have a link between two roots.

    ``sets`` (fp, root, group, size, set) is materialized. i and j are chunks, side tells which of two a row is of. Wide groups (those that are
    cut) are one for each ``CELL`` classes or ``CELL_BYTES`` at most, so they and their chunks are broadcast and the sets move once.
    """
    limit = lambda n, size: (F.col(n) > CELL) | (F.col(size) * 8 > CELL_BYTES)
    per = sets.groupBy("group", "root").agg(F.count("*").alias("n"), F.sum("size").alias("size"))
    wide = per.groupBy("group").agg(F.sum("n").alias("n"), F.sum("size").alias("size"), F.collect_list(F.when(limit("n", "size"), F.col("root"))).alias("large"))
    wide = C.materialize(wide.filter(limit("n", "size")).select("group", "large"), "wide-groups")

    step = max(1e-9, -math.log(max(similarity, 1e-9))) * (1 + 1e-9)  # sizes that a link can have are in one band or in two neighbours
    rows = sets.join(F.broadcast(wide), "group", "left")
    rows = rows.withColumn("own", F.when(F.array_contains("large", F.col("root")), F.col("root")))
    rows = rows.withColumn("band", F.when(F.col("large").isNotNull(), F.floor(F.log(F.greatest("size", F.lit(1))) / step)))
    rows = rows.withColumn("part", F.when(F.col("band").isNotNull(), F.concat_ws(":", "band", "own"))).drop("large")
    g = F.ceil(F.greatest(F.count("*") / CELL, F.sum("size") * 8 / CELL_BYTES, F.lit(1))).cast("int").alias("g")
    parts = C.materialize(rows.filter("part is not null").groupBy("group", "part", "band", "own").agg(g), "parts")

    chunk = lambda part, at: F.concat_ws("/", part, at)
    a, b = parts.alias("a"), parts.alias("b")
    meet = (F.col("a.group") == F.col("b.group")) & (F.abs(F.col("a.band") - F.col("b.band")) <= 1) & ~F.coalesce(F.col("a.own") == F.col("b.own"), F.lit(False))
    others = F.transform(F.sequence(F.lit(0), F.col("b.g") - 1), lambda at: chunk(F.col("b.part"), at))
    meets = a.join(b, meet).groupBy("a.group", "a.part", "a.g").agg(F.flatten(F.collect_list(others)).alias("others"))
    rows = rows.join(F.broadcast(C.materialize(meets, "meeting-chunks")), ["group", "part"], "left")
    rows = rows.withColumn("mine", F.when(F.col("part").isNull(), "").otherwise(chunk(F.col("part"), F.pmod(F.xxhash64("fp"), F.col("g")))))
    rows = rows.withColumn("other", F.explode(F.when(F.col("part").isNull(), F.array(F.lit(""))).otherwise(F.col("others"))))
    return rows.select("group", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"), (F.col("mine") < F.col("other")).alias("side"), "fp", "root", "set")


def links(crowd: DataFrame, texts: DataFrame, shingle: int, similarity: float) -> DataFrame:
    """(a, b): links whose connected groups are those of all candidates (classes that share a key) at ``similarity`` or more.

    ``crowd``: (key, fp) of each shared key, ``texts``: (fp, text), one row per class.
    """
    spark = crowd.sparkSession
    dealt = crowd.select("key", "fp").repartitionByRange("key", "fp").sortWithinPartitions("key", "fp")
    turns = C.materialize(dealt.mapInArrow(_neighbours, "part int, key long, a long, b long"), "neighbours")
    ends = sorted(tuple(r) for r in turns.filter("part is not null").select("part", "b", "key", "a").collect())  # two rows of a task
    cut = [(x[3], y[3]) for x, y in zip(ends[1::2], ends[2::2], strict=False) if x[2] == y[2] and x[3] != y[3]]
    pairs = turns.filter("part is null").select("a", "b").union(spark.createDataFrame(cut, "a long, b long"))
    pairs = C.materialize(pairs.distinct(), "pairs")
    left, right = (texts.select(F.col("fp").alias(c), F.col("text").alias(f"text_{c}")) for c in ("a", "b"))
    full = pairs.join(left, "a").join(right, "b").select("a", "b", "text_a", "text_b")
    first = C.materialize(full.mapInArrow(_verify(shingle, similarity), "a long, b long"), "first-links")
    C.release(spark)

    roots = connected_components(first, "a", "b")
    rooted = C.materialize(texts.select("fp").join(roots, F.col("fp") == F.col("node"), "left").select("fp", F.coalesce("root", "fp").alias("root")), "rooted-classes")
    of = lambda c: rooted.select(F.col("fp").alias(c), F.col("root").alias(f"root_{c}"))
    apart = pairs.join(of("a"), "a").join(of("b"), "b").filter("root_a <> root_b").select(F.least("root_a", "root_b").alias("a"), F.greatest("root_a", "root_b").alias("b"))
    group = connected_components(C.materialize(apart.distinct(), "parts-apart"), "a", "b")  # neighbours of a key hold it together, so all its parts are of one group
    sized = group.withColumnRenamed("root", "group").join(rooted.groupBy("root").agg(F.count("*").alias("_n")), F.col("node") == F.col("root")).select("root", "group", "_n")
    members = C.join_hot(rooted, sized, "root", rooted.count()).drop("_n")
    C.release(spark)
    sets = members.join(texts, "fp").select("fp", "root", "group", "text").mapInArrow(_sets(shingle), "fp long, root long, group long, size long, set binary")
    met = cells(C.materialize(sets, "open-sets"), similarity)
    dealt = met.repartitionByRange("group", "i", "j").sortWithinPartitions("group", "i", "j")  # by range: cells are few and large, and a hash would deal several to one task
    return first.union(dealt.mapInArrow(_compare_cells(similarity), "a long, b long"))


def _told(what: DataFrame) -> DataFrame:
    """(_slot, told): for every task the list of ``what`` (_slot, _row, told), which has all its rows, in their order."""
    return what.groupBy("_slot").agg(F.sort_array(F.collect_list(F.struct("_row", "told"))).alias("all")).select("_slot", F.col("all.told").alias("told"))


class Found(NamedTuple):
    stored: DataFrame  # the documents as rows (_in, _slot, _row)
    slots: int
    rows: DataFrame  # (doc_id, fp, _slot, _row)
    classes: DataFrame  # (fp, first, _n): first is the component's first document (no id, doc_id, _slot, _row)


def find(docs: DataFrame, key: str, text: str, shingle: int, similarity: float) -> Found:
    """Classes and components. Texts are stored once, where they lie, and only those of candidates are moved."""
    stored, slots = C.stored_by_task(docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_in")), "documents")
    of = lambda c: F.col(f"_in.`{c}`")
    slim = stored.select(of(key).cast("long").alias("doc_id"), of(text).cast("binary").alias("text"), "_slot", "_row")
    rows = C.materialize(slim.mapInArrow(_classes(shingle), "doc_id long, fp long, print binary, _slot int, _row long"), "shingle-classes")
    least = F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "_slot", "_row")
    classes = C.materialize(rows.groupBy("fp").agg(F.min(least).alias("least"), F.count("*").alias("_n")), "classes")
    prints = C.materialize(rows.groupBy("fp").agg(F.first("print").alias("print")), "prints")
    crowd = C.materialize(anchors.crowds(prints), "crowds")
    C.release(docs.sparkSession)

    chosen = classes.join(crowd.select("fp").distinct(), "fp", "left_semi").select("fp", "least", "_n")
    whose = C.join_hot(rows.select("fp", "_slot", "_row"), classes.join(chosen.select("fp", F.lit(True).alias("wanted")), "fp", "left"), "fp", rows.count())
    own = F.col("wanted") & (F.col("least._slot") == F.col("_slot")) & (F.col("least._row") == F.col("_row"))
    side = _told(whose.select("_slot", "_row", F.when(own, F.col("fp")).alias("told")))
    texts = C.beside(stored, slots, side).select(F.get("told", F.col("_row").cast("int")).alias("fp"), of(text).cast("binary").alias("text")).filter("fp is not null")
    texts = C.materialize(texts, "candidate-texts")
    C.release(docs.sparkSession)
    roots = connected_components(links(crowd, texts, shingle, similarity), "a", "b")
    found = C.materialize(with_component(classes, roots).withColumnRenamed("component_id", "first"), "components")
    C.release(docs.sparkSession)
    return Found(stored, slots, rows.drop("print"), found)


def near_duplicates(docs: DataFrame, key: str, text: str, shingle: int, similarity: float) -> DataFrame:
    """(doc_id, fp, component_id) for every document; fp is its class, component_id the smallest doc_id reachable over links."""
    found = find(docs, key, text, shingle, similarity)
    joined = C.join_hot(found.rows, found.classes, "fp", found.rows.count())
    return joined.select("doc_id", "fp", F.col("first.doc_id").alias("component_id"))


def survivors(docs: DataFrame, key: str, text: str, shingle: int, similarity: float) -> DataFrame:
    """The rows of ``docs`` less all but one of each component: the one with the smallest id (none is the largest), then the first stored."""
    found = find(docs, key, text, shingle, similarity)
    joined = C.join_hot(found.rows, found.classes, "fp", found.rows.count())
    keep = (F.col("first._slot") == F.col("_slot")) & (F.col("first._row") == F.col("_row"))
    side = _told(joined.select("_slot", "_row", keep.alias("told")))
    return C.beside(found.stored, found.slots, side).filter(F.get("told", F.col("_row").cast("int"))).select("_in.*")
