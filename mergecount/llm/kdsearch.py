"""Exact top-k search by inner product: a KD-tree per shard, best-first.

Vectors are dealt to cells of space, the leaves of median splits of a bounded sample (``SAMPLE``; it only
decides where rows go), and each cell is cut by a hash of the id into shards of about ``SHARD_ROWS``, so
equal or clustered vectors spread evenly. A shard's tree splits at the median of the widest side of a
node's tight bounding box until ``LEAF`` rows are left or all are equal; it is stored as one row.
Queries are dealt to blocks of about ``BLOCK`` rows in the same cells.

Each block first searches a shard of its own cell; the kth best (score, id) found there bounds all that
follows. Then blocks and shards are paired by their boxes alone: a shard whose box admits no inner product
that reaches the least kth of a block is dropped before any vector moves. A block's vectors go once to
each group of ``GROUP`` shards that it still needs, meet the shards there one after another, and carry
the kth best from shard to shard. Within a tree a query takes leaves best-first, by the largest
inner product that their boxes admit, until none can beat its current kth. Results of all groups meet
per query. ``visited`` counts what was looked at. Where boxes can't tell vectors apart (64 independent
dimensions), every leaf has to be looked at and the search is a blocked product of all pairs.

Edge cases: vectors that are null, or hold null or non-finite components, take no part; vectors are
compared with those of the same number of components; ties go to the smaller id; an id that occurs
in several rows is searched once for each of them, and never finds itself; fewer than k candidates
give all; an empty table gives an empty result; other columns are ignored. Components are scaled to
integers; scores are exact, and a component whose products could pass 63 bits raises.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from . import common as C

SCALE, K, SHARD_ROWS, LEAF, BLOCK, GROUP, SAMPLE = 1024, 10, 4096, 256, 1024, 64, 32_768
LEAST, LAST = -(1 << 63), (1 << 63) - 1


class Tree(NamedTuple):
    ids: np.ndarray
    vectors: np.ndarray
    begin: np.ndarray  # of each leaf
    end: np.ndarray
    lo: np.ndarray
    hi: np.ndarray
    least_id: np.ndarray


def _narrow(v: np.ndarray) -> np.ndarray:
    """The same integers in the smallest type that holds them."""
    top = int(np.abs(v).max(initial=0))
    return v.astype(np.int16 if top < 1 << 15 else np.int32 if top < 1 << 31 else np.int64)


def build(ids: np.ndarray, vectors: np.ndarray, leaf: int = LEAF) -> Tree:
    """Median splits at the widest side of tight boxes; the leaves in the order of their rows."""
    order = np.lexsort((ids,))
    spans, leaves = [(0, len(ids))], []
    while spans:
        a, b = spans.pop()
        own = vectors[order[a:b]]
        lo, hi = own.min(axis=0), own.max(axis=0)
        side = hi - lo
        if b - a <= leaf or not side.any():
            leaves.append((a, b, lo, hi, ids[order[a:b]].min()))
            continue
        mid = (b - a) // 2
        order[a:b] = order[a:b][np.argpartition(own[:, int(side.argmax())], mid)]
        spans += [(a, a + mid), (a + mid, b)]
    return Tree(ids[order], _narrow(vectors[order]), *(np.array([x[i] for x in leaves]) for i in range(5)))


def exact_type(tree_max: int, query_max: int, dims: int):
    """Doubles are exact (and faster) while all sums stay below 2**53."""
    most = dims * max(1, tree_max) * max(1, query_max)
    if most >= 1 << 63:
        raise OverflowError("scores of these vectors can pass 63 bits: use a smaller scale")
    return np.float64 if most < 1 << 53 else np.int64


class Best:
    """The k best (score, id) of each query so far, best first, and the limit that others must reach."""

    def __init__(self, kth: np.ndarray, kth_id: np.ndarray, k: int):
        self.scores, self.ids = np.full((len(kth), k), LEAST), np.full((len(kth), k), LAST)
        self.limit, self.limit_id, self.visited = kth.copy(), kth_id.copy(), 0

    def offer(self, q: np.ndarray, ids: np.ndarray, scores: np.ndarray) -> None:
        """Candidates ``scores`` [query, id] for the queries ``q``; LEAST for none."""
        k = self.scores.shape[1]
        all_scores = np.concatenate([self.scores[q], scores], axis=1)
        floor = np.maximum(np.partition(all_scores, -k, axis=1)[:, -k], np.maximum(self.limit[q], LEAST + 1))
        row, column = np.nonzero(all_scores >= floor[:, None])
        value = all_scores[row, column]
        one = np.where(column < k, self.ids[q[row], np.minimum(column, k - 1)], ids[np.maximum(column - k, 0)])
        order = np.lexsort((one, -value, row))
        row, value, one = row[order], value[order], one[order]
        place = np.arange(len(row)) - np.searchsorted(row, row)
        kept = place < k
        new_scores, new_ids = np.full((len(q), k), LEAST), np.full((len(q), k), LAST)
        new_scores[row[kept], place[kept]], new_ids[row[kept], place[kept]] = value[kept], one[kept]
        self.scores[q], self.ids[q] = new_scores, new_ids
        last, last_id = new_scores[:, -1], new_ids[:, -1]
        closer = (last > self.limit[q]) | (last == self.limit[q]) & (last_id < self.limit_id[q])
        self.limit[q], self.limit_id[q] = np.where(closer, last, self.limit[q]), np.where(closer, last_id, self.limit_id[q])


def search(tree: Tree, ids: np.ndarray, queries: np.ndarray, best: Best) -> None:
    """Offers what a tree has to ``best``: every query takes its leaves best-first, all queries of a leaf at once."""
    if not len(queries):
        return
    kind = exact_type(int(np.abs(tree.vectors).max(initial=0)), int(np.abs(queries).max(initial=0)), queries.shape[1])
    vectors, wide = tree.vectors.astype(kind), queries.astype(kind)
    bounds = (np.maximum(wide, 0) @ tree.hi.astype(kind).T + np.minimum(wide, 0) @ tree.lo.astype(kind).T).astype(np.int64)
    order = np.argsort(-bounds, axis=1, kind="stable")
    alive = np.arange(len(queries))
    for turn in range(order.shape[1]):
        leaf = order[alive, turn]
        bound = bounds[alive, leaf]
        alive, leaf, bound = (x[bound >= best.limit[alive]] for x in (alive, leaf, bound))  # later leaves have lower bounds
        if not len(alive):
            break
        worth = (bound > best.limit[alive]) | (tree.least_id[leaf] <= best.limit_id[alive])
        best.visited += int(worth.sum())
        for one in np.unique(leaf[worth]):
            q = alive[worth & (leaf == one)]
            a, b = tree.begin[one], tree.end[one]
            scores = (wide[q] @ vectors[a:b].T).astype(np.int64)
            scores[tree.ids[a:b][None, :] == ids[q][:, None]] = LEAST
            best.offer(q, tree.ids[a:b], scores)


def split_space(sample: np.ndarray, depth: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """Axis and median of every node, level by level."""
    cell, levels = np.zeros(len(sample), dtype=np.int64), []
    for d in range(depth):
        axis, median = np.zeros(1 << d, dtype=np.int64), np.zeros(1 << d)
        for node in range(1 << d):
            own = sample[cell == node]
            if len(own):
                axis[node] = int((own.max(axis=0) - own.min(axis=0)).argmax())
                median[node] = np.median(own[:, axis[node]])
        levels.append((axis, median))
        cell = cell * 2 + (sample[np.arange(len(sample)), axis[cell]] > median[cell])
    return levels


def cell_of(levels: list[tuple[np.ndarray, np.ndarray]], vectors: np.ndarray) -> np.ndarray:
    cell, rows = np.zeros(len(vectors), dtype=np.int64), np.arange(len(vectors))
    for axis, median in levels:
        cell = cell * 2 + (vectors[rows, axis[cell]] > median[cell])
    return cell


def whole_vectors(table: DataFrame, key: str, vector: str, scale: int = SCALE) -> DataFrame:
    """(id, dims, v): usable vectors as integers."""
    col = F.col(vector)
    wide = lambda x: x.cast("double")
    fine = F.forall(col, lambda x: F.coalesce(~F.isnan(wide(x)) & (F.abs(wide(x)) < F.lit(float("inf"))), F.lit(False)))
    good = table.filter(F.col(key).isNotNull() & col.isNotNull() & fine)
    return good.select(F.col(key).cast("long").alias("id"), F.size(col).alias("dims"), F.transform(col, lambda x: F.floor(wide(x) * scale).cast("long")).alias("v"))


def _matrix(column: pa.Array, dims: int) -> np.ndarray:
    flat = np.asarray(column.flatten().to_numpy(zero_copy_only=False), dtype=np.int64)
    return flat.reshape(len(column), dims)


def _groups(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[tuple[tuple, pa.Table]]:
    """Runs of equal keys of sorted batches."""
    held: list[pa.RecordBatch] = []
    now: tuple | None = None
    for batch in batches:
        if not batch.num_rows:
            continue
        columns = [np.asarray(batch.column(i).to_numpy(zero_copy_only=False)) for i in range(keys)]
        change = np.flatnonzero(np.logical_or.reduce([c[1:] != c[:-1] for c in columns])) + 1
        cuts = [0, *change.tolist(), batch.num_rows]
        for a, b in zip(cuts, cuts[1:], strict=False):
            key = tuple(int(c[a]) for c in columns)
            if key != now and held:
                yield now, pa.Table.from_batches(held)
                held = []
            now = key
            held.append(batch.slice(a, b - a))
    if held:
        yield now, pa.Table.from_batches(held)


_PACKED = "dims int, part long, lo array<long>, hi array<long>, kth long, blob binary"


def _packed_batch(dims: int, part: int, vectors: np.ndarray, kth: int, content) -> pa.RecordBatch:
    sides = [pa.array([v.astype(np.int64).tolist()], pa.list_(pa.int64())) for v in (vectors.min(axis=0), vectors.max(axis=0))]
    columns = [pa.array([dims], pa.int32()), pa.array([part], pa.int64()), *sides, pa.array([kth], pa.int64()), pa.array([pickle.dumps(content, protocol=5)], pa.binary())]
    return pa.RecordBatch.from_arrays(columns, names=["dims", "part", "lo", "hi", "kth", "blob"])


def _packed(make) -> object:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for (dims, part), rows in _groups(batches, 2):
            rows = rows.combine_chunks()
            ids = np.asarray(rows.column("id").to_numpy(), dtype=np.int64)
            vectors = _matrix(rows.column("v").combine_chunks(), dims)
            yield _packed_batch(dims, part, vectors, LEAST, make(ids, vectors))

    return run


def _in_cells(vectors: DataFrame, planes, name: str) -> DataFrame:
    """(dims, cell, id, v) in the shared folder; ``planes``: broadcast splits by number of components."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            dims = np.asarray(batch.column(1).to_numpy(zero_copy_only=False))
            cell = np.zeros(len(dims), dtype=np.int64)
            for d in np.unique(dims):
                rows = np.flatnonzero(dims == d)
                cell[rows] = cell_of(planes.value.get(int(d), []), _matrix(batch.column(2).take(pa.array(rows)), int(d)))
            yield pa.RecordBatch.from_arrays([batch.column(1), pa.array(cell), batch.column(0), batch.column(2)], names=["dims", "cell", "id", "v"])

    return C.materialize(vectors.select("id", "dims", "v").mapInArrow(run, "dims int, cell long, id long, v array<long>"), name)


def _parts(rows: DataFrame, size: int, make, name: str) -> DataFrame:
    """One packed row for each part: a cell, or a part of a cell of over ``size`` rows by the hash of the id."""
    parts = rows.groupBy("dims", "cell").agg(F.ceil(F.count("*") / size).alias("parts"))
    dealt = rows.join(parts, ["dims", "cell"]).select("dims", (F.col("cell") * (1 << 31) + F.pmod(F.xxhash64("id", F.lit(name)), F.col("parts"))).alias("part"), "id", "v")
    sorted_rows = dealt.repartitionByRange("dims", "part").sortWithinPartitions("dims", "part")  # ranges of parts are even, hashes of few parts are not
    return C.materialize(sorted_rows.mapInArrow(_packed(make), _PACKED), name)


def _at_home(k: int):
    """Rows (dims, block, queries, tree): the block with the kth best that the tree gives."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for dims, block, queries, tree in zip(*[batch.column(i) for i in range(4)], strict=True):
                ids, q, kth, kth_id = pickle.loads(queries.as_py())
                best = Best(kth, kth_id, k)
                if tree.as_py() is not None:
                    search(pickle.loads(tree.as_py()), ids, q, best)
                yield _packed_batch(dims.as_py(), block.as_py(), q, int(best.limit.min()), (ids, q, best.limit, best.limit_id))

    return run


def _needed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (dims, part, group, lo, hi, kth, shards) of blocks: those with shards of the group whose boxes reach the block's least kth, and these shards."""
    for batch in batches:
        out, parts = [], []
        for i in range(batch.num_rows):
            lo, hi = (np.array(batch.column(c)[i].as_py(), dtype=np.float64) for c in (3, 4))
            shards = batch.column(6)[i].as_py()
            los, his = (np.array([x[c] for x in shards], dtype=np.float64) for c in ("lo", "hi"))
            most = np.maximum(np.maximum(lo * los, lo * his), np.maximum(hi * los, hi * his)).sum(axis=1)
            most = most + np.abs(most) * 1e-9 + 1  # doubles may round
            own = [x["part"] for x, m in zip(shards, most, strict=True) if m >= batch.column(5)[i].as_py()]
            if own:
                out.append(i)
                parts.append(own)
        kept = [batch.column(c).take(pa.array(out, pa.int64())) for c in range(3)]
        yield pa.RecordBatch.from_arrays([*kept, pa.array(parts, pa.list_(pa.int64()))], names=["dims", "block", "group", "parts"])


def _found(k: int):
    """Rows (dims, block, group, queries, tree), those of a block and group in a row: its k best there, kth carried from tree to tree."""
    kinds = [pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64()]
    names = ["dims", "block", "no", "query_id", "vec_id", "score", "visited"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, ids, q, best = None, None, None, None

        def done() -> pa.RecordBatch:
            no, place = np.nonzero(best.scores > LEAST)
            rows = len(no) + 1  # the first row has the count alone
            lead = lambda x, first: np.concatenate([[first], x])
            columns = [np.full(rows, now[0]), np.full(rows, now[1]), lead(no, -1), lead(ids[no], 0), lead(best.ids[no, place], 0), lead(best.scores[no, place], 0), lead(np.zeros(len(no)), best.visited)]
            return pa.RecordBatch.from_arrays([pa.array(c.astype(np.int64)).cast(t) for c, t in zip(columns, kinds, strict=True)], names=names)

        for batch in batches:
            for dims, block, group, queries, tree in zip(*[batch.column(i) for i in range(5)], strict=True):
                key = (dims.as_py(), block.as_py(), group.as_py())
                if key != now:
                    if now is not None:
                        yield done()
                    now = key
                    ids, q, kth, kth_id = pickle.loads(queries.as_py())
                    best = Best(kth, kth_id, k)
                search(pickle.loads(tree.as_py()), ids, q, best)
        if now is not None:
            yield done()

    return run


def _met(vectors: DataFrame, queries: DataFrame, k: int, leaf: int) -> tuple[DataFrame, int]:
    """What every block finds in every group of shards that it needs, and the number of vectors."""
    spark = vectors.sparkSession
    total = vectors.count()
    depth = max(0, min(12, (-(-total // SHARD_ROWS) - 1).bit_length()))  # at least 8 rows of a full sample in a cell
    share = F.pmod(F.xxhash64("id", F.lit("sample")), F.lit(1 << 40)) < int((1 << 40) * min(1.0, SAMPLE / max(1, total)))
    seen: dict[int, list] = {}
    for r in vectors.filter(share).select("dims", "v").limit(SAMPLE).collect() if depth else []:
        seen.setdefault(r["dims"], []).append(r["v"])
    planes = spark.sparkContext.broadcast({d: split_space(np.array(v, dtype=np.int64).reshape(len(v), d), depth if d else 0) for d, v in seen.items()})

    index = _parts(_in_cells(vectors, planes, "vector-cells"), SHARD_ROWS, lambda ids, v: build(ids, v, leaf), "trees").withColumnRenamed("blob", "tree")
    fresh = lambda ids, v: (ids, _narrow(v), np.full(len(ids), LEAST), np.full(len(ids), LAST))
    sets = _parts(_in_cells(queries, planes, "query-cells"), BLOCK, fresh, "query-blocks").withColumnRenamed("part", "block")
    cell = lambda c: F.shiftright(c, 31)
    homes = index.groupBy("dims", cell("part").alias("cell")).agg(F.min("part").alias("part")).join(index.select("dims", "part", "tree"), ["dims", "part"])
    home = sets.withColumn("cell", cell("block")).join(homes.select("dims", "cell", "tree"), ["dims", "cell"], "left").select("dims", "block", "blob", "tree")
    bounded = C.materialize(home.mapInArrow(_at_home(k), _PACKED), "query-bounds").withColumnRenamed("part", "block")

    groups = max(1, -(-index.count() // GROUP))
    group = F.pmod(F.xxhash64("part"), F.lit(groups)).alias("group")
    boxes = index.select("dims", group, F.struct("part", "lo", "hi").alias("box")).groupBy("dims", "group").agg(F.collect_list("box").alias("shards"))  # about GROUP each
    every = bounded.select("dims", "block", "lo", "hi", "kth", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(groups - 1).cast("long"))).alias("group"))
    pairs = every.join(boxes, ["dims", "group"]).select("dims", "block", "group", "lo", "hi", "kth", "shards")
    needed = C.materialize(pairs.mapInArrow(_needed, "dims int, block long, group long, parts array<long>"), "block-groups")
    sent = needed.join(bounded.select("dims", "block", "blob"), ["dims", "block"])
    trees = index.select("dims", group, "part", "tree").hint("merge")
    met = sent.join(trees, ["dims", "group"]).filter(F.array_contains("parts", F.col("part"))).select("dims", "block", "group", "blob", "tree")
    return met.mapInArrow(_found(k), "dims int, block long, no long, query_id long, vec_id long, score long, visited long"), total


def top_k(vectors: DataFrame, queries: DataFrame, k: int = K, leaf: int = LEAF) -> DataFrame:
    """(query_id, rank, vec_id, score): the k best rows of ``vectors`` for each row of ``queries`` (both from whole_vectors)."""
    found, _ = _met(vectors, queries, k, leaf)
    rank = F.row_number().over(W.partitionBy("dims", "block", "no").orderBy(F.desc("score"), "vec_id"))
    return found.filter("no >= 0").withColumn("rank", rank).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def visited(vectors: DataFrame, queries: DataFrame, k: int = K, leaf: int = LEAF) -> float:
    """Share of all pairs of queries and leaves (of ``leaf`` rows) that a search looks at after the home shard."""
    found, total = _met(vectors, queries, k, leaf)
    return (found.agg(F.sum("visited")).first()[0] or 0) * leaf / max(1, queries.count() * total)


def op2_kdtree_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ten best other vectors of every vector whose id is divisible by 100."""
    vectors = whole_vectors(C.table(spark, sf_dir, "embeddings"), "vec_id", "embedding")
    return top_k(vectors, vectors.filter("id % 100 = 0"))


def oracle() -> str:
    return f"""
    with v as (select vec_id, list_transform(embedding, lambda x: floor({SCALE} * x::DOUBLE)::BIGINT) e from embeddings
      where embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0),
    s as (select q.vec_id query_id, v.vec_id, list_sum(list_transform(range(1, len(v.e) + 1), lambda i: q.e[i] * v.e[i]))::BIGINT score
      from v q join v on q.vec_id % 100 = 0 and q.vec_id <> v.vec_id and len(q.e) = len(v.e))
    select query_id, row_number() over (partition by query_id order by score desc, vec_id)::INTEGER as rank, vec_id, score from s
    qualify row_number() over (partition by query_id order by score desc, vec_id) <= {K}"""
