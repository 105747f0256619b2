"""Mixture-controlled packing by deficit round-robin.

Every source is a queue of tokens (its documents one after another, each closed by an end id).
In each round all open queues earn tokens by their target weights, ``window`` tokens together; a
queue is served whole quanta of ``QUANTUM`` tokens and carries what it has earned beyond them (its
deficit) to the next round. What is served, in round and queue order, is cut in windows of exactly
``window`` tokens. So every window holds the target proportions within a quantum per queue, the
running error of a queue never exceeds one quantum, and only the last window has padding, up to a
power of two. An empty queue's share goes to the others by weight. The default weights are the
sources' own sizes: all queues end together and all documents are packed.

What a queue has earned after r rounds is a closed formula of r, so no window needs the one before
it: a document's pieces follow from its place in its queue. Deficits thereby carry over windows and
partitions without any serial pass. Tokens are computed once and written to the shared folder, a bucket
for each task; the places come from sums by task and source, which go to where the tokens lie
(``common.beside``), so tokens are never shuffled, at any size.

A queue's order is that of the stored tasks and their rows, so another layout of the input packs in
another order. Every source has a queue. The schedule (two numbers for each source) is broadcast and
the work for a piece grows with the number of sources.

Edge cases: a null text is empty and packs its end id alone; a null source is a source; repeated
rows are packed each; an empty table gives an empty result; very long texts span many windows;
extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from . import common as C
from .tokens import WordTokenizer

WINDOW, QUANTUM, END = 4096, 256, 2
#: Entries (pieces times queues) placed at once.
_CELLS = 1 << 22


def tokenizer_definition(path: str | None = None) -> str:
    """Text of a tokenizer file (about 2 MB, whatever the data), to be shipped to the executors."""
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("word_bpe_49k.json")
    with open(path, encoding="utf-8") as f:
        return f.read()


def _tokenize(definition, end: int) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok, seen = WordTokenizer.shared(definition.value), {}  # of each source its number in this task and its tokens so far
        last = np.array([end], dtype=tok.dtype).tobytes()
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                piece = batch.slice(at, 512)
                sources = piece.column(1).to_pylist()
                ids = [tok.encode(t.as_py() or "") + last for t in piece.column(2)]
                sizes, starts, numbers = [len(x) // tok.dtype.itemsize for x in ids], [], []
                for source, n in zip(sources, sizes, strict=True):
                    own = seen.setdefault(source, [len(seen), 0])
                    numbers.append(own[0])
                    starts.append(own[1])
                    own[1] += n
                columns = [piece.column(0), piece.column(1), pa.array(numbers, pa.int32()), pa.array(starts, pa.int64()), pa.array(sizes, pa.int64()), pa.array(ids, pa.binary())]
                yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "source", "number", "before", "doc_tokens", "ids"])

    return run


class Schedule:
    """Deficit round-robin over queues of ``totals`` tokens with target ``weights``."""

    def __init__(self, totals: list[int], weights: list[float], window: int = WINDOW, quantum: int = QUANTUM):
        self.totals = np.array(totals, dtype=np.int64)
        self.weights = np.array(weights, dtype=np.float64)
        self.window, self.quantum = window, quantum
        times = self.totals / self.weights  # of each queue's end, in tokens per unit of weight
        self.times = np.concatenate([[0.0], np.unique(times)])
        self.earned = np.array([np.minimum(self.totals, self.weights * v).sum() for v in self.times])
        self.rounds = -(-int(self.totals.sum()) // window)

    def served(self, rounds: np.ndarray) -> np.ndarray:
        """Tokens that each queue has been served after so many rounds: one row per entry of ``rounds``."""
        time = np.interp(rounds.astype(np.float64) * self.window, self.earned, self.times)
        credit = np.minimum(self.totals, time[:, None] * self.weights)
        whole = (np.floor(credit / self.quantum) * self.quantum).astype(np.int64)
        done = (credit >= self.totals * (1 - 1e-12)) | (rounds >= self.rounds)[:, None]
        return np.where(done, self.totals, np.minimum(whole, self.totals))

    def place(self, queue: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Place in the whole served order of the tokens ``at`` of their queues, and the queue's token at which the service that holds each ends."""
        goal = np.minimum((at // self.quantum + 1) * self.quantum, self.totals[queue])
        total = np.interp(goal / self.weights[queue], self.times, self.earned)
        r = np.clip(np.ceil(total / self.window).astype(np.int64) - 1, 0, self.rounds - 1)
        rows = np.arange(len(r))
        while True:  # rounding can be off by a round
            now, nxt = self.served(r), self.served(r + 1)
            move = (nxt[rows, queue] <= at).astype(np.int64) - (now[rows, queue] > at)
            if not move.any():
                break
            r = r + move
        earlier = np.where(np.arange(len(self.totals))[None, :] < queue[:, None], nxt - now, 0).sum(axis=1)
        return now.sum(axis=1) + earlier + at - now[rows, queue], nxt[rows, queue]


def cut_pieces(schedule: Schedule, queue: np.ndarray, begin: np.ndarray, size: np.ndarray) -> Iterator[tuple[np.ndarray, ...]]:
    """(row, start, length, sequence, offset) arrays for documents at begin..begin+size of their queues."""
    q, window = schedule.quantum, schedule.window
    first, parts = begin // q, (begin + size - 1) // q - begin // q + 1
    ends = np.cumsum(parts)
    many = max(64, _CELLS // len(schedule.totals))
    for at in range(0, int(ends[-1]) if len(ends) else 0, many):  # so much at once, however long a document is
        k = np.arange(at, min(at + many, int(ends[-1])))
        row = np.searchsorted(ends, k, side="right")
        lo = np.maximum(begin[row], (first[row] + k - (ends[row] - parts[row])) * q)
        hi = np.minimum(begin[row] + size[row], (lo // q + 1) * q)
        place, _ = schedule.place(queue[row], lo)
        new = np.ones(len(k), dtype=bool)
        new[1:] = (row[1:] != row[:-1]) | (place[1:] != place[:-1] + (hi - lo)[:-1])
        starts = np.flatnonzero(new)
        row, lo, place = row[starts], lo[starts], place[starts]
        hi = hi[np.append(starts[1:], len(k)) - 1]
        windows = (place + hi - lo - 1) // window - place // window + 1
        back = np.repeat(np.arange(len(row)), windows)
        nth = np.arange(len(back)) - np.repeat(np.cumsum(windows) - windows, windows)
        left = np.maximum(place[back], (place[back] // window + nth) * window)
        right = np.minimum((place + hi - lo)[back], (left // window + 1) * window)
        yield row[back], lo[back] + left - place[back] - begin[row[back]], right - left, left // window, left % window


def _pieces(schedule: Schedule, dtype: np.dtype, with_ids: bool) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                part = batch.slice(at, 1024)
                queue, begin, size = (np.asarray(part.column(i).to_numpy(zero_copy_only=False), dtype=np.int64) for i in (1, 2, 3))
                ids = [np.frombuffer(x.as_py(), dtype=dtype).astype("<u4") for x in part.column(4)]
                for row, start, length, sequence, offset in cut_pieces(schedule, queue, begin, size):
                    own = [ids[r][s : s + n] for r, s, n in zip(row, start, length, strict=True)]
                    crc = [zlib.crc32(x) for x in own]
                    columns = [part.column(0).take(pa.array(row)), *map(pa.array, (start, length)), pa.array(crc, pa.int64()), *map(pa.array, (size[row], sequence, offset)), pa.array(queue[row].astype(np.int32))]
                    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "queue"]
                    if with_ids:
                        columns.append(pa.array([x.tolist() for x in own], pa.list_(pa.int64())))
                        names.append("ids")
                    yield pa.RecordBatch.from_arrays(columns, names=names)

    return run


def pack(docs: DataFrame, weights: dict[str | None, float] | None = None, window: int = WINDOW, quantum: int = QUANTUM, end: int = END, tokenizer: str | None = None, with_ids: bool = True) -> DataFrame:
    """Pieces of ``docs`` (doc_id, source, text): doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, queue (and ids).

    ``weights``: target weights by source (positive); a source without one has its own size as weight if
    no weights are given, else the least of those given.
    """
    spark = docs.sparkSession
    definition = spark.sparkContext.broadcast(tokenizer_definition(tokenizer))
    dtype = WordTokenizer(definition.value).dtype
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), F.col("text").cast("string").alias("text"))
    schema = "doc_id long, source string, number int, before long, doc_tokens long, ids binary"
    tokens, slots = C.stored_by_task(slim.mapInArrow(_tokenize(definition, end), schema), "tokens")
    sums = C.materialize(tokens.groupBy("_slot", "number", "source").agg(F.sum("doc_tokens").alias("n")), "token-sums")
    queues = [(r["source"], r["n"]) for r in sums.groupBy("source").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), F.asc_nulls_last("source")).collect()]
    if not queues:
        return tokens.select("doc_id", *[F.lit(0).cast("long").alias(c) for c in ("start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")], F.lit(0).alias("queue"), *([F.array().cast("array<long>").alias("ids")] if with_ids else []))
    least = min(weights.values()) if weights else 0
    schedule = Schedule([n for _, n in queues], [float(n if weights is None else weights.get(s, least)) for s, n in queues], window, quantum)
    numbers = spark.createDataFrame([(s, i) for i, (s, _) in enumerate(queues)], "of string, queue int")
    before = W.partitionBy("queue").orderBy("_slot").rowsBetween(W.unboundedPreceding, -1)  # a row for each task
    bases = sums.join(numbers, F.col("source").eqNullSafe(F.col("of"))).select("_slot", "number", "queue", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    side = bases.groupBy("_slot").agg(F.sort_array(F.collect_list(F.struct("number", "queue", "base"))).alias("bases"))
    own = C.beside(tokens, slots, side).withColumn("_base", F.get("bases", F.col("number")))
    placed = own.select("doc_id", F.col("_base.queue").cast("long").alias("queue"), (F.col("_base.base") + F.col("before")).alias("begin"), "doc_tokens", "ids")
    out = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, queue int" + (", ids array<long>" if with_ids else "")
    return placed.mapInArrow(_pieces(schedule, dtype, with_ids), out)


def op4_mixture_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents packed in sequences of at most 4096 tokens, one row per piece."""
    return pack(C.table(spark, sf_dir, "documents"), with_ids=False)
