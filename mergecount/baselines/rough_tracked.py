"""Sequential baselines: a cut that follows a rough estimate, with an error state.

Every table keeps offsets above a cut; the cut follows a running rough estimate (the median of some
pairwise largest-level counters: monotone, within a constant factor). If the offsets ever cost more
than the budget, the table fails for good. The rough estimate depends on the order of arrival, so
there is no merge. ``copies`` repeats it with independent seeds; ``walk`` draws their seeds by an
expander walk and keeps the rough states as differences from a common base (the simple case only).
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..cuts import cell_bits
from ..functions.expander import WalkSpace
from ..functions.families import LevelHash
from ..functions.seeding import Seed, draw
from ..sketch import Context, rho_inv

ROUGH = 9


def rough_hashes(context: Context) -> list[list[LevelHash]]:
    """Level functions of each table's rough counters: drawn one by one, or along a walk where the tables' own are."""
    p, mask = context.params, (1 << context.params.d) - 1
    if context.seed.mode == "independent":
        pair = lambda t, r: (draw(context.fingerprint, p.d, f"rough-{t}-{r}-{x}") for x in "ab")
        numbers = [a | b << p.d for t in range(p.l) for r in range(ROUGH) for a, b in [pair(t, r)]]
    else:
        space = WalkSpace(2 * p.d, math.log(16), p.l * ROUGH)
        numbers = space.unrank(draw(context.fingerprint, space.bits, "rough-walk"))
    made = [LevelHash([x & mask, x >> p.d], p.d) for x in numbers]
    return [made[t * ROUGH : (t + 1) * ROUGH] for t in range(p.l)]


class RoughTracked:
    def __init__(self, context: Context):
        p = context.params
        self.context = context
        self.levels = np.full((p.l, p.b), -1, dtype=np.int16)
        self.cut = np.zeros(p.l, dtype=np.int64)
        self.failed = np.zeros(p.l, dtype=bool)
        self.rough = np.full((p.l, ROUGH), -1, dtype=np.int64)
        self.hashes = rough_hashes(context)

    def add(self, keys: np.ndarray) -> RoughTracked:
        """Keys in order of arrival. A cut moves at every key that raises the rough estimate."""
        p = self.context.params
        for t, triple in enumerate(self.context.triples):
            level, bins = triple.many(keys)
            rough = np.maximum.accumulate(np.stack([np.maximum.accumulate(h.many(keys).astype(np.int64)) for h in self.hashes[t]]), axis=1)
            rough = np.maximum(rough, self.rough[t][:, None])
            cuts = np.maximum(np.maximum(0, np.sort(rough, axis=0)[ROUGH // 2] - p.log_b + 1), self.cut[t])
            edges = np.concatenate([[0], np.flatnonzero(np.diff(cuts)) + 1, [len(keys)]])
            for a, b in zip(edges, edges[1:], strict=False):  # between two moves of the cut
                if a == b or self.failed[t]:
                    continue
                self.levels[t] = np.maximum(self.levels[t] - (cuts[a] - self.cut[t]), -1)
                self.cut[t] = cuts[a]
                new = np.maximum(level[a:b].astype(np.int64) - cuts[a], -1)
                kept = new >= 0
                np.maximum.at(self.levels[t], bins[a:b][kept], new[kept].astype(np.int16))
                self.failed[t] |= bool(cell_bits(self.levels[t]).sum() > p.budget * p.b)
            if len(keys):
                self.rough[t] = rough[:, -1]
        return self

    def merge(self, other: RoughTracked) -> RoughTracked:
        raise TypeError("this counter is sequential: its cut depends on the order of arrival")

    def estimate(self) -> float:
        p = self.context.params
        values = np.exp2(self.cut) * rho_inv((self.levels >= 0).sum(axis=1), p.b)
        good = values[~self.failed]
        return float(np.median(good)) if len(good) else float("nan")

    def rough_bits(self, delta_coded: bool) -> int:
        """Bits of the rough states: whole numbers, or a common base and differences (walk-seeded variant)."""
        whole = self.context.params.d.bit_length()
        if not delta_coded:
            return self.rough.size * whole
        base = np.median(self.rough, axis=None).astype(int)
        return whole + int((2 * cell_bits(np.abs(self.rough - base) - 1) + 2).sum())  # a gamma code of difference + 1, and a sign

    def bits(self, delta_coded: bool) -> int:
        """Bits of the whole state: offsets in the self-delimiting code, cuts, rough states."""
        return int((2 * cell_bits(self.levels) + 1).sum()) + self.context.params.l * self.context.params.d.bit_length() + self.rough_bits(delta_coded)


def by_group(df: DataFrame, key: str, order: str, seed: Seed, group: list[str]) -> DataFrame:
    """(group..., estimate, failed_tables, bits, delta_bits): keys folded in order, one task for each group (there is no other way).

    A key that comes again changes no state (maxima only grow, and its own were taken), so a group's task gets each key once, at its first place.
    """
    rows = df.filter(F.col(key).isNotNull()).groupBy(*group, F.col(key).cast("long").alias("_key")).agg(F.min(order).alias("_order")).select(*group, "_order", "_key")
    schema = T.StructType([*[rows.schema[g] for g in group], T.StructField("estimate", T.DoubleType()), T.StructField("failed_tables", T.IntegerType()), T.StructField("bits", T.LongType()), T.StructField("delta_bits", T.LongType())])
    dealt = rows.repartition(*group).sortWithinPartitions(*group, "_order")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: RoughTracked | None = None
        now: tuple | None = None
        kinds = None

        def done() -> pa.RecordBatch:
            columns = [pa.array([v], kinds[i]) for i, v in enumerate(now)]
            return pa.RecordBatch.from_arrays([*columns, pa.array([held.estimate()]), pa.array([int(held.failed.sum())], pa.int32()), pa.array([held.bits(False)], pa.int64()), pa.array([held.bits(True)], pa.int64())], names=[*group, "estimate", "failed_tables", "bits", "delta_bits"])

        for batch in batches:
            kinds = [batch.column(i).type for i in range(len(group))]
            names = list(zip(*[batch.column(i).to_pylist() for i in range(len(group))], strict=True))
            keys = np.asarray(batch.column(len(group) + 1).to_numpy()).astype(np.int64).view(np.uint64)
            edges = [0, *[i for i in range(1, len(names)) if names[i] != names[i - 1]], len(names)]
            for a, b in zip(edges, edges[1:], strict=False):
                if a == b:
                    continue
                if names[a] != now:
                    if held is not None:
                        yield done()
                    held, now = RoughTracked(Context.of(seed)), names[a]
                held.add(keys[a:b])
        if held is not None:
            yield done()

    return dealt.mapInArrow(run, schema)

