"""Histogram sort: shards of near-equal bytes from splitters found by counting exact bytes below candidate keys.

Rows are ordered by (hash of the text, doc_id), so equal texts lie side by side and share a shard unless a boundary
has to fall among them. Each round counts the bytes and rows below a set of probes on every partition of a narrow table,
adds them up, and puts new probes into the intervals that still hold an unmet target. Only probe counts reach the driver.
The rows are then exchanged once.
"""

from __future__ import annotations

from bisect import bisect_left

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import Workspace, few_files

LOW, HIGH = -(1 << 63), (1 << 63) - 1


class Splitter:
    """A boundary search: the key interval that holds it, and the weight and rows below both ends."""

    def __init__(self, target: float, slack: float, low: int, high: int, total: int, rows: int):
        self.target, self.slack = target, slack
        self.low, self.below_low, self.rows_low = low, 0, 0
        self.high, self.below_high, self.rows_high = high, total, rows

    def learn(self, key: int, below: int, rows: int) -> None:
        if below <= self.target and key > self.low:
            self.low, self.below_low, self.rows_low = key, below, rows
        if below >= self.target and key < self.high:
            self.high, self.below_high, self.rows_high = key, below, rows

    def best(self) -> tuple[float, int, int, int]:
        """(distance, key, weight below, rows below) of the nearer end."""
        return min((abs(b - self.target), k, b, r) for k, b, r in ((self.low, self.below_low, self.rows_low), (self.high, self.below_high, self.rows_high)))

    def met(self) -> bool:
        return self.best()[0] <= self.slack

    def open(self) -> bool:
        return not self.met() and self.high - self.low > 1 and self.rows_high - self.rows_low > 1

    def probes(self, n: int) -> list[int]:
        step = (self.high - self.low) / (n + 1)
        return sorted({min(max(self.low + int(step * (i + 1)), self.low + 1), self.high - 1) for i in range(n)})


def _histogram(column: str, probes: list[int]):
    """For each partition: the number, weight and rows of each gap between probes (gap g: probes[g-1] <= key < probes[g])."""
    edges = np.array(probes, dtype=np.int64)

    def run(batches):
        weight, rows = np.zeros(len(edges) + 1, dtype=np.int64), np.zeros(len(edges) + 1, dtype=np.int64)
        for batch in batches:
            keys = batch.column(0).to_numpy(zero_copy_only=False)
            gap = np.searchsorted(edges, keys, side="right")
            weight += np.bincount(gap, weights=batch.column(1).to_numpy(zero_copy_only=False), minlength=len(edges) + 1).astype(np.int64)
            rows += np.bincount(gap, minlength=len(edges) + 1)
        used = np.flatnonzero(rows)
        yield pa.RecordBatch.from_arrays([pa.array(used, pa.int64()), pa.array(weight[used]), pa.array(rows[used])], names=["gap", "weight", "n"])

    return run


def refine(narrow: DataFrame, key: str, targets: list[tuple[float, float]], total: int, rows: int, fan: int = 31, most_rounds: int = 30) -> list[Splitter]:
    """Splitters over a long column of ``narrow`` (with ``size``) for (target weight, slack) pairs."""
    found = [Splitter(t, s, LOW, HIGH, total, rows) for t, s in targets]
    for _ in range(most_rounds):
        probes = sorted({p for s in found if s.open() for p in s.probes(fan)})
        if not probes:
            break
        counts = narrow.select(key, "size").mapInArrow(_histogram(key, probes), "gap long, weight long, n long").groupBy("gap").agg(F.sum("weight").alias("weight"), F.sum("n").alias("n")).collect()
        weight, n = np.zeros(len(probes) + 1, dtype=np.int64), np.zeros(len(probes) + 1, dtype=np.int64)
        for r in counts:
            weight[r.gap], n[r.gap] = r.weight, r.n
        below, under = np.cumsum(weight)[:-1], np.cumsum(n)[:-1]
        for s in found:
            for i in range(max(0, bisect_left(probes, s.low) - 1), min(len(probes), bisect_left(probes, s.high) + 1)):
                s.learn(probes[i], int(below[i]), int(under[i]))
    return found


def shard_by_bytes(spark, docs: DataFrame, shards: int = 24, tolerance: float = 0.002, slice_bytes: int = 8 << 20, most_slices: int = 16384) -> DataFrame:
    """``docs`` with shard (int) and slot (long, gapless from 0 in each shard, in key order).

    The size of a row is the UTF-8 bytes of its text plus 8, null text counting as none. A shard's bytes differ from the
    mean by ``tolerance`` of it at most, or by the rows next to its boundaries where these are larger. Equal rows may be
    parted, in which case all of them stay. Rows without doc_id come before others of the same text. The columns shard
    and slot of the input, if any, are replaced. An empty table gives an empty result.
    """
    work = Workspace(spark, "shards")
    text = F.coalesce(F.col("text"), F.lit(""))
    key = F.xxhash64(text)
    tie = F.coalesce(F.col("doc_id").cast("long"), F.lit(LOW + 1))
    docs = docs.drop("shard", "slot")
    narrow = work.put(docs.select(key.alias("k"), tie.alias("tie"), (F.octet_length(text) + 8).cast("long").alias("size")), "narrow")
    total, rows = narrow.agg(F.coalesce(F.sum("size"), F.lit(0)), F.count(F.lit(1))).first()
    # shards are cut into slices, the unit of the exchange; inner boundaries need no more than rough balance
    each = max(1, min(most_slices // shards, -(-total // (shards * slice_bytes))))
    ideal = total / shards
    targets = [(ideal * i / each, tolerance * ideal if i % each == 0 else 0.25 * ideal / each) for i in range(1, shards * each)]
    found = refine(narrow, "k", targets, total, rows)
    # (k, tie, rows below): a boundary inside one hash value is sought among the doc_ids of that value
    bounds, inner = [], {}
    for i, s in enumerate(found):
        _, k, _, under = s.best()
        bounds.append((k, LOW, under))
        if not s.met() and s.high - s.low == 1 and s.rows_high - s.rows_low > 1:
            inner.setdefault(s.low, []).append(i)
    for k, members in inner.items():
        group = narrow.where(F.col("k") == k).select("tie", "size")
        start, before = found[members[0]].below_low, found[members[0]].rows_low
        size, n = found[members[0]].below_high - start, found[members[0]].rows_high - before
        for i, s in zip(members, refine(group, "tie", [(found[i].target - start, found[i].slack) for i in members], size, n)):
            bounds[i] = (k, s.best()[1], before + s.best()[3])
    bounds.sort()
    edges = [(LOW, LOW, 0), *bounds]
    ks, ties, unders = (np.array(x, dtype=np.int64) for x in zip(*edges))
    shard_start = unders[::each]

    @F.pandas_udf("long")
    def slice_of(k, tie):
        import pandas as pd

        keys, ids = k.to_numpy(), tie.to_numpy()
        at = np.searchsorted(ks, keys, side="right") - 1
        equal = np.flatnonzero(ks[at] == keys)
        for i in equal:  # only keys that a boundary has hit
            a = at[i]
            while a > 0 and ks[a] == keys[i] and ties[a] > ids[i]:
                a -= 1
            at[i] = a
        return pd.Series(at)

    place = docs.withColumn("_k", key).withColumn("_tie", tie).withColumn("_slice", slice_of("_k", "_tie"))
    order = Window.partitionBy("_slice").orderBy("_k", "_tie")
    starts = F.array(*[F.lit(int(unders[j] - shard_start[j // each])) for j in range(len(unders))])
    ranked = place.withColumn("_at", F.row_number().over(order))
    slot = F.element_at(starts, (F.col("_slice") + 1).cast("int")) + F.col("_at") - 1
    placed = ranked.withColumn("shard", F.floor(F.col("_slice") / each).cast("int")).withColumn("slot", slot.cast("long")).drop("_k", "_tie", "_slice", "_at")
    return few_files(placed, rows, 10_000)
