"""SimHash prints of shingle sets in many blocks, and groups of prints that share an anchor of a block.

A print has ``BLOCKS`` blocks of 23 bits, each bit set where over half of the set's hashes have it. A block's
anchors are the 4,096 words of the perfect Golay code of length 23 (covering radius 3): every value lies
within 3 bits of exactly one, so a print goes to one anchor for each block. Two large sets at Jaccard similarity s
differ in a bit with probability arccos(2s / (1 + s)) / pi or less, 0.1515 at 0.8. Then a block has the same anchor for both
with probability 0.121, and all ``BLOCKS`` blocks differ for 2 pairs of 100,000. Among small sets of 0.8 or more, 12 of 15 members
differ in 0.161 of the bits (7 pairs of 100,000). Only four of five members differ in more (0.19), so a set of
``SMALL`` members goes as its subsets less one member too, and such pairs always meet.

Prints of one anchor are compared by their first ``SKETCH`` words: those within ``NEAR`` of 192 bits (29 expected at
0.8, 96 for sets that have nothing in common) are linked, and every group of linked prints is one crowd
for the exact check that follows. An anchor with over ``CELL`` prints is cut in chunks and compared by pairs
of chunks, in as many tasks; the loads are counted before any copy is made.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as C

BLOCK, BLOCKS, SKETCH, NEAR, CELL, SMALL = 23, 84, 3, 52, 1 << 15, 5
WORDS = -(-BLOCK * BLOCKS // 64)
_RNG = np.random.default_rng(64)
_TIMES = _RNG.integers(0, 1 << 63, WORDS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_PLUS = _RNG.integers(0, 1 << 63, WORDS, dtype=np.uint64)
_MIX = np.uint64(0xD6E8FEB86659FD93)
_PIECE = 255  # sums of so many rows fit in a byte
_SKETCH = [f"s{k}" for k in range(SKETCH)]


def print_of(own: np.ndarray) -> np.ndarray:
    """The print of a sorted set of 64-bit hashes, as ``WORDS`` words; where half of them have a bit, one member decides, drawn anew for each word."""
    counts = np.zeros(64 * WORDS, dtype=np.int64)
    for at in range(0, len(own), _PIECE):
        bits = own[at : at + _PIECE, None] * _TIMES + _PLUS
        bits ^= bits >> np.uint64(32)
        bits *= _MIX
        bits ^= bits >> np.uint64(32)
        each = np.unpackbits(bits.view(np.uint8), axis=1)
        counts += each.sum(axis=0, dtype=np.uint8)
        if not at:
            first = np.unpackbits(bits[(bits * _MIX).argmin(axis=0), np.arange(WORDS)].view(np.uint8))
    return np.packbits(counts * 2 + first > len(own)).view(np.uint64) if len(own) else np.zeros(WORDS, dtype=np.uint64)


def prints_of(own: np.ndarray) -> np.ndarray:
    """The rows of words that a set goes by: its print, and for ``SMALL`` members those of its subsets less one."""
    less = range(len(own)) if len(own) == SMALL else ()
    return np.stack([print_of(own), *[print_of(np.delete(own, i)) for i in less]])


def _golay() -> tuple[np.ndarray, np.ndarray]:
    """Syndromes of the values of 12 bits (of the low and of the high half), and the least error of each syndrome."""
    place = []
    for i in range(BLOCK):
        rest = 1 << i
        for j in range(i, 10, -1):
            rest ^= (0xAE3 << (j - 11)) if rest >> j & 1 else 0
        place.append(rest)
    half = np.zeros((2, 1 << 12), dtype=np.int64)
    for i, one in enumerate(place):
        half[i // 12] ^= np.where(np.arange(1 << 12) >> (i % 12) & 1, one, 0)
    error = np.full(1 << 11, -1, dtype=np.int64)
    for wrong in itertools.chain.from_iterable(itertools.combinations(range(BLOCK), w) for w in range(4)):
        syndrome = 0
        for i in wrong:
            syndrome ^= place[i]
        error[syndrome] = sum(1 << i for i in wrong)
    return half, error


_HALF, _ERROR = _golay()


def nearest(values: np.ndarray) -> np.ndarray:
    """The one code word within 3 bits of each 23-bit value."""
    return values ^ _ERROR[_HALF[0][values & 0xFFF] ^ _HALF[1][values >> 12]]


def anchors_of(prints: np.ndarray) -> np.ndarray:
    """For each print (rows of ``WORDS`` words) the anchor of every block: 4096 times the block, and the word's upper 12 bits, which tell the others."""
    bits = np.unpackbits(np.ascontiguousarray(prints).view(np.uint8), axis=1)[:, : BLOCK * BLOCKS]
    values = bits.reshape(len(prints), BLOCKS, BLOCK).astype(np.int64) @ (np.int64(1) << np.arange(BLOCK))
    return (np.arange(BLOCKS) << 12) + (nearest(values) >> 11)


def _words(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The prints of a column of binary values, and for each value how many it holds."""
    whole = column.to_pylist()
    return np.frombuffer(b"".join(whole), dtype=np.uint64).reshape(-1, WORDS), np.array([len(x) for x in whole]) // (8 * WORDS)


def _loads(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    total = np.zeros(BLOCKS << 12, dtype=np.int64)
    for batch in batches:
        total += np.bincount(anchors_of(_words(batch.column(1))[0]).ravel(), minlength=len(total))
    at = np.flatnonzero(total)
    yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], names=["anchor", "n"])


def _replicate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A row for each print and block: its anchor, the class and the sketch."""
    for batch in batches:
        for at in range(0, batch.num_rows, 512):
            part = batch.slice(at, 512)
            prints, held = _words(part.column(1))
            fp = np.repeat(np.asarray(part.column(0).to_numpy(zero_copy_only=False), dtype=np.int64), held)
            sketch = [pa.array(np.repeat(prints[:, k].view(np.int64), BLOCKS)) for k in range(SKETCH)]
            yield pa.RecordBatch.from_arrays([pa.array(anchors_of(prints).ravel()), pa.array(np.repeat(fp, BLOCKS)), *sketch], names=["anchor", "fp", *_SKETCH])


def _near(many: list[np.ndarray], one: list) -> np.ndarray:
    """Which of ``many`` sketches, as a column for each word, are within ``NEAR`` bits of ``one``."""
    bits = np.bitwise_count(many[0] ^ one[0])
    for x, y in zip(many[1:], one[1:], strict=True):
        bits = bits + np.bitwise_count(x ^ y)
    return bits <= NEAR


def groups(sketch: list[np.ndarray]) -> list[np.ndarray]:
    """Places of each group of at least two sketches (a column for each word) that are linked, directly or over others."""
    at = np.arange(len(sketch[0]))
    if len(at) <= 256:  # mostly nothing is near: told for all at once
        at = np.flatnonzero(_near([x[:, None] for x in sketch], sketch).sum(axis=1) > 1)
    left, out = [x[at] for x in sketch], []
    while len(at) > 1:
        group, front = [at[:1]], [[x[0] for x in left]]
        at, left = at[1:], [x[1:] for x in left]
        while front and len(at):
            hit = _near(left, front.pop())
            if hit.any():
                group.append(at[hit])
                front += list(zip(*[x[hit] for x in left], strict=True))
                at, left = at[~hit], [x[~hit] for x in left]
        if len(group) > 1:
            out.append(np.concatenate(group))
    return out


def _crowds(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (cell, fp, sketch) sorted by cell: (key, fp) of each group; the same members give the same key in every cell."""
    import xxhash

    def found(cols: list[np.ndarray]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        for at in groups([x.view(np.uint64) for x in cols[2:]]):
            own = np.unique(cols[1][at])  # one class can be there by several prints
            if len(own) > 1:
                yield np.full(len(own), xxhash.xxh64_intdigest(own.tobytes()), dtype=np.uint64).view(np.int64), own

    def told(cells: list[list[np.ndarray]]) -> pa.RecordBatch:
        rows = [x for cell in cells for x in found(cell)]
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate(x) if rows else [], pa.int64()) for x in (list(zip(*rows, strict=True)) or [(), ()])], names=["key", "fp"])

    held: list[list[np.ndarray]] = []  # pieces of the cell that is still open
    for batch in batches:
        cols = [np.asarray(c.to_numpy(zero_copy_only=False), dtype=np.int64) for c in batch.columns]
        if not len(cols[0]):
            continue
        ends = [0, *(np.flatnonzero(cols[0][1:] != cols[0][:-1]) + 1).tolist(), len(cols[0])]
        done = []
        for x, y in zip(ends, ends[1:], strict=False):
            if held and held[0][0][0] != cols[0][x]:
                done.append([np.concatenate(c) for c in zip(*held, strict=True)])
                held = []
            held.append([c[x:y] for c in cols])
        yield told(done)
    if held:
        yield told([[np.concatenate(c) for c in zip(*held, strict=True)]])


def crowds(prints: DataFrame) -> DataFrame:
    """(key, fp): the groups of classes that are linked within some anchor's cell. ``prints`` (fp, print: all of ``prints_of``) is materialized, a row for each class."""
    loads = prints.mapInArrow(_loads, "anchor long, n long").groupBy("anchor").agg(F.sum("n").alias("n"))
    hot = C.materialize(loads.filter(F.col("n") > CELL).select("anchor", F.ceil(F.col("n") / (CELL // 2)).cast("int").alias("g")), "hot-anchors")
    copies = prints.mapInArrow(_replicate, ", ".join(f"{c} long" for c in ("anchor", "fp", *_SKETCH)))
    cut = copies.join(F.broadcast(hot), "anchor", "left").withColumn("g", F.coalesce("g", F.lit(1)))
    cut = cut.withColumn("c", F.pmod(F.xxhash64("fp"), F.col("g")).cast("long"))
    cut = cut.withColumn("o", F.explode(F.sequence(F.lit(0).cast("long"), F.col("g").cast("long") - 1)))
    cell = (F.least("c", "o") * (1 << 20) + F.greatest("c", "o")) * (1 << 20) + F.col("anchor")
    dealt = cut.select(cell.alias("cell"), "fp", *_SKETCH).repartition("cell").sortWithinPartitions("cell")
    return dealt.mapInArrow(_crowds, "key long, fp long").distinct()
