"""SimHash near-duplicates by anchor-point covering.

A text's fingerprint has a bit where over half of its 3-word shingles' hashes have it. Two
fingerprints are linked at ``THRESHOLD`` (3) or fewer differing bits. If they are, one of two
disjoint blocks of 31 bits differs in at most one bit. On a block the anchors are the words of the
perfect Hamming code of length 31 (covering radius 1), so of two values at distance 1 or less, both
lie within 1 + 1 = 2 bits of one anchor. Every fingerprint goes to all anchors within 2 of each
block (1 or 16 of 2^26), and fingerprints are compared per anchor; no link can be missed.

Equal fingerprints are one class before anything is compared. An anchor's comparison gives stars
from the least member of each group found, never all pairs. Anchors with over ``CELL`` fingerprints are cut in
chunks and compared chunk by chunk, in as many tasks as there are pairs of chunks; those that would be
a large part of all copies are counted and cut before anything is shuffled (``hot_anchors``).
Components come from star contractions (``components``).

Edge cases: null, empty and blank texts have fingerprint zero, linked like any other; texts of one
or two words have one shingle; very long texts are hashed in pieces; an empty table gives an empty
result; repeated rows are copies; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C
from . import jaccard
from .components import connected_components, with_component

THRESHOLD, SHINGLE, SEED = 3, 3, 42
BLOCK_BITS, BLOCK_SHIFTS = 31, (0, 31)
CELL = 4096
_LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
_PIECE = 1 << 16


def fingerprint(text: bytes | None) -> int:
    """64-bit fingerprint of a UTF-8 text, as a signed integer."""
    import xxhash

    words = (text or b"").translate(_LOWER).split()
    if not words:
        return 0
    if len(words) < SHINGLE:
        shingles = [b" ".join(words)]
    else:
        shingles = None
    digest, counts, n = xxhash.xxh64_digest, np.zeros(64, dtype=np.int64), max(1, len(words) - SHINGLE + 1)
    for at in range(0, n, _PIECE):
        if shingles is None:
            part = words[at : at + _PIECE + SHINGLE - 1]
            hashes = [digest(b"%b %b %b" % three, SEED) for three in zip(part, part[1:], part[2:], strict=False)]
        else:
            hashes = [digest(s, SEED) for s in shingles]
        bits = np.unpackbits(np.frombuffer(b"".join(hashes), dtype=np.uint8).reshape(-1, 8), axis=1)
        for k in range(0, len(bits), 255):  # sums of 255 rows fit in a byte
            counts += bits[k : k + 255].sum(axis=0, dtype=np.uint8)
    return int(np.packbits(counts * 2 > n).view(">i8")[0])


def _fingerprints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array((fingerprint(t.as_py()) for t in batch.column(1)), pa.int64())], names=["doc_id", "fp"])


def fingerprints(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, fp): one row per document, fp as a signed long."""
    slim = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).cast("binary").alias("text"))
    return slim.mapInArrow(_fingerprints, "doc_id long, fp long")


def anchors_of(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Row numbers and anchors: all code words within 2 bits of each 31-bit value."""
    values = values.astype(np.int64)
    syndrome = np.zeros(len(values), dtype=np.int64)
    for place in range(1, BLOCK_BITS + 1):
        syndrome ^= np.where((values >> (place - 1)) & 1, place, 0)
    rows, found = [np.arange(len(values))], [np.where(syndrome > 0, values ^ (1 << np.maximum(syndrome - 1, 0)), values)]
    for i in range(1, BLOCK_BITS + 1):
        j = syndrome ^ i
        ok = np.flatnonzero((syndrome > 0) & (j > i))  # i and j differ, neither is zero: each pair once
        rows.append(ok)
        found.append(values[ok] ^ (1 << (i - 1)) ^ (1 << (j[ok] - 1)))
    return np.concatenate(rows), np.concatenate(found)


def _replicate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        whole = np.asarray(batch.column(0).to_numpy(zero_copy_only=False), dtype=np.int64)
        for at in range(0, len(whole), 8192):
            fp = whole[at : at + 8192]
            for block, shift in enumerate(BLOCK_SHIFTS):
                rows, anchors = anchors_of((fp.view(np.uint64) >> np.uint64(shift)).astype(np.int64) & ((1 << BLOCK_BITS) - 1))
                yield pa.RecordBatch.from_arrays([pa.array(anchors * 2 + block), pa.array(fp[rows])], names=["anchor", "fp"])


def stars(fps: np.ndarray, side: np.ndarray | None = None) -> list[tuple[int, int]]:
    """Links from the least member of each group of fingerprints connected at THRESHOLD; with ``side`` only links between two sides count."""
    out, left, sides = [], np.array(fps, dtype=np.int64), side
    while len(left) > 1:
        group, front = [int(left[0])], [(left[0], None if sides is None else sides[0])]
        left, sides = left[1:], None if sides is None else sides[1:]
        while front and len(left):
            one, own = front.pop()
            near = np.bitwise_count((left ^ one).view(np.uint64)) <= THRESHOLD
            if sides is not None:
                near &= sides != own
            if near.any():
                front += list(zip(left[near], sides[near], strict=True)) if sides is not None else [(x, None) for x in left[near]]
                group += left[near].tolist()
                left, sides = left[~near], None if sides is None else sides[~near]
        least = min(group)
        out += [(x, least) for x in group if x != least]
    return out


def _runs(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[tuple[list[np.ndarray], np.ndarray]]:
    """Sorted batches as columns with starts of runs of equal keys; no run is cut."""
    held: list[list[np.ndarray]] = []  # pieces of the run that is still open
    for batch in batches:
        cols = [np.asarray(c.to_numpy(zero_copy_only=False)) for c in batch.columns]
        if not len(cols[0]):
            continue
        last = len(cols[0]) - 1
        same = np.logical_and.reduce([c == c[last] for c in cols[:keys]])
        cut = int(np.flatnonzero(same)[0])  # where the batch's last run begins
        goes_on = bool(held) and all(h[-1] == c[0] for h, c in zip(held[-1][:keys], cols[:keys], strict=True))
        if not cut and goes_on:
            held.append(cols)
            continue
        whole = [np.concatenate(x) for x in zip(*held, [c[:cut] for c in cols], strict=True)]
        if len(whole[0]):
            yield whole, _starts(whole, keys)
        held = [[c[cut:] for c in cols]]
    if held:
        whole = [np.concatenate(x) for x in zip(*held, strict=True)]
        yield whole, _starts(whole, keys)


def _starts(cols: list[np.ndarray], keys: int) -> np.ndarray:
    new = np.logical_or.reduce([c[1:] != c[:-1] for c in cols[:keys]])
    return np.concatenate([[0], np.flatnonzero(new) + 1, [len(cols[0])]])


def _links(kind: list, a: list, b: list) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.concatenate(x) if x else [], pa.int64()) for x in (kind, a, b)], names=["kind", "a", "b"])


def _compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (anchor, fp) sorted by anchor: links (kind -1, a, b), and rows of crowded anchors (kind: the anchor, a: fp)."""
    for (anchor, fp), starts in _runs(batches, 1):
        kinds, lefts, rights = [], [], []
        sizes = np.diff(starts)
        for size in range(2, min(8, int(sizes.max())) + 1):  # small groups: all at once
            at = starts[:-1][sizes == size]
            for i in range(size):
                for j in range(i + 1, size):
                    x, y = fp[at + i], fp[at + j]
                    near = np.bitwise_count((x ^ y).view(np.uint64)) <= THRESHOLD
                    kinds.append(np.full(int(near.sum()), -1)), lefts.append(x[near]), rights.append(y[near])
        for k in np.flatnonzero(sizes > 8):
            own = fp[starts[k] : starts[k + 1]]
            if len(own) > CELL:
                kinds.append(np.full(len(own), anchor[starts[k]])), lefts.append(own), rights.append(own)
            elif found := stars(own):
                x = np.array(found, dtype=np.int64)
                kinds.append(np.full(len(x), -1)), lefts.append(x[:, 0]), rights.append(x[:, 1])
        yield _links(kinds, lefts, rights)


def _compare_cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for (_, i, j, side, fp), starts in _runs(batches, 3):
        lefts = []
        for x, y in zip(starts[:-1], starts[1:], strict=True):
            lefts += stars(fp[x:y], None if i[x] == j[x] else side[x:y])
        if lefts:
            x = np.array(lefts, dtype=np.int64)
            yield _links([np.full(len(x), -1)], [x[:, 0]], [x[:, 1]])


def _blocks(fp: Column) -> list[Column]:
    mask = F.lit((1 << BLOCK_BITS) - 1).cast("long")
    return [F.struct(F.lit(i).cast("long").alias("block"), F.shiftright(fp, shift).bitwiseAND(mask).alias("value")) for i, shift in enumerate(BLOCK_SHIFTS)]


def _anchors_of_values(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        block, value, n = (np.asarray(c.to_numpy(zero_copy_only=False), dtype=np.int64) for c in batch.columns)
        rows, anchors = anchors_of(value)
        yield pa.RecordBatch.from_arrays([pa.array(anchors * 2 + block[rows]), pa.array(n[rows])], names=["anchor", "n"])


def hot_anchors(fps: DataFrame, copies: int, floor: int = CELL) -> DataFrame:
    """(anchor, n): anchors with over ``floor`` and over 1 / HOT of all copies, HOT at most; counted by the blocks' values, before any copy is made.

    An anchor has at most 1 + 31 + 465 values within 2 bits, so only one near a value that over
    limit / 497 fingerprints share can be hot.
    """
    limit = max(floor, copies // C.HOT)
    values = fps.select(F.explode(F.array(*_blocks(F.col("fp")))).alias("b")).groupBy("b.block", "b.value").agg(F.count("*").alias("n"))
    values = C.materialize(values, "block-values")
    near = "anchor long, n long"
    dense = values.filter(F.col("n") > limit // 497)
    if not dense.limit(1).count():
        return values.sparkSession.createDataFrame([], near)
    candidates = dense.mapInArrow(_anchors_of_values, near).select("anchor").distinct()
    loads = values.mapInArrow(_anchors_of_values, near).join(candidates, "anchor", "left_semi").groupBy("anchor").agg(F.sum("n").alias("n"))
    return C.materialize(loads.filter(F.col("n") > limit), "hot-anchors")


def links(fps: DataFrame, floor: int = CELL) -> DataFrame:
    """(a, b): links whose connected groups are those of all pairs of distinct fingerprints within THRESHOLD bits. ``fps`` is materialized."""
    hot = hot_anchors(fps, 34 * fps.count(), floor)
    copies = fps.mapInArrow(_replicate, "anchor long, fp long")
    dealt = copies.join(F.broadcast(hot.select("anchor")), "anchor", "left_anti").repartition("anchor").sortWithinPartitions("anchor")
    found = C.materialize(dealt.mapInArrow(_compare, "kind long, a long, b long"), "anchors")
    crowded = found.filter("kind >= 0").select(F.col("kind").alias("anchor"), F.col("a").alias("fp"))
    chunks = lambda n: F.ceil(n / (CELL // 2)).cast("int").alias("g")
    cut = crowded.join(crowded.groupBy("anchor").agg(chunks(F.count("*"))), "anchor")
    cut = cut.unionByName(copies.join(F.broadcast(hot.select("anchor", chunks(F.col("n")))), "anchor"))
    cut = cut.withColumn("c", F.pmod(F.xxhash64("fp"), F.col("g")).cast("int"))
    cut = cut.withColumn("o", F.explode(F.sequence(F.lit(0), F.col("g") - 1)))
    cells = cut.select("anchor", F.least("c", "o").alias("i"), F.greatest("c", "o").alias("j"), F.col("c").alias("side"), "fp")
    dealt = cells.repartition("anchor", "i", "j").sortWithinPartitions("anchor", "i", "j")
    more = dealt.mapInArrow(_compare_cells, "kind long, a long, b long")
    return found.filter("kind < 0").select("a", "b").union(more.select("a", "b"))


def digest_duplicates(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, fp, component_id) for every document by op8's law (``SHINGLE``, ``THRESHOLD``); component_id is the smallest doc_id reachable over links."""
    rows = C.materialize(fingerprints(docs, key, text), "fingerprints")
    classes = C.materialize(rows.groupBy("fp").agg(F.min("doc_id").alias("least"), F.count("*").alias("_n")), "classes")
    roots = connected_components(links(classes.select("fp")), "a", "b")
    of_class = C.materialize(with_component(classes, roots), "components")
    return C.join_hot(rows, of_class, "fp", rows.count()).select("doc_id", "fp", "component_id")


def near_duplicates(docs: DataFrame, key: str = "doc_id", text: str = "text", shingle: int = 5, similarity: float = 0.8) -> DataFrame:
    """(doc_id, fp, component_id) by the pipeline's law: Jaccard of ``shingle``-word sets at least ``similarity`` (see ``jaccard``)."""
    return jaccard.near_duplicates(docs, key, text, shingle, similarity)


def survivors(docs: DataFrame, key: str = "doc_id", text: str = "text", shingle: int = 5, similarity: float = 0.8) -> DataFrame:
    """``docs`` with one row of each component of ``near_duplicates``; rows without an id, and several of one id, count as any others."""
    return jaccard.survivors(docs, key, text, shingle, similarity)


def op8_simhash_anchors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprint and component of every document."""
    found = digest_duplicates(C.table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
