"""Counts of all pairs of frequent items, over the whole database.

Map tasks add up triangles of their own and send on the cells that are not zero, so a pair costs a row for each task at most. Rows are taken in slices
of bounded pairs, so a task holds its triangle and one slice, whatever the rows' number and length.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Items up to which a task keeps the whole triangle; beyond it keeps only cells met, and sends them on when there are FLUSH.
DENSE_ITEMS, FLUSH = 2000, 2_000_000


#: Pairs that are looked at together.
SLICE = 1_000_000


def _pairs_of(offsets: np.ndarray, items: np.ndarray, weight: np.ndarray, n: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Keys hi * (n + 1) + lo and weights of the pairs of each row, SLICE or the pairs of one row at a time."""
    sizes = np.diff(offsets)
    for size in np.unique(sizes[sizes > 1]).tolist():
        of = np.flatnonzero(sizes == size)
        pairs = size * (size - 1) // 2
        step = max(1, SLICE // pairs)
        if pairs > SLICE:  # very long rows: an item with all before it, some at a time
            for r in of.tolist():
                m = items[offsets[r] : offsets[r + 1]].astype(np.int64)
                for hi in range(1, size):
                    yield m[hi] * (n + 1) + m[:hi], np.full(hi, weight[r])
            continue
        lo, hi = np.triu_indices(size, 1)
        for at in range(0, len(of), step):
            some = of[at : at + step]
            m = items[offsets[some][:, None] + np.arange(size)[None, :]].astype(np.int64)
            yield (m[:, hi] * (n + 1) + m[:, lo]).ravel(), np.repeat(weight[some], pairs)


def pair_matrix(ranked: DataFrame, n: int) -> DataFrame:
    """(hi, lo, pair_count), lo < hi, for pairs that occur; ranked has items and, if collapsed, weight."""
    w = F.col("weight") if "weight" in ranked.columns else F.lit(1).cast("long")

    def run(batches):
        dense = np.zeros((n + 1) * (n + 1), np.int64) if n <= DENSE_ITEMS else None
        held: dict[int, int] = {}

        def out(key, count):
            return pa.RecordBatch.from_arrays([pa.array((key // (n + 1)).astype(np.int32)), pa.array((key % (n + 1)).astype(np.int32)), pa.array(count)], names=["hi", "lo", "n"])

        for b in batches:
            lists = b.column(0)
            for key, weight in _pairs_of(lists.offsets.to_numpy() - lists.offsets[0].as_py(), pc.list_flatten(lists).to_numpy(zero_copy_only=False), b.column(1).to_numpy(), n):
                if dense is not None and 4 * len(key) > len(dense):
                    dense += np.bincount(key, weight, minlength=len(dense)).astype(np.int64)
                    continue
                made, which = np.unique(key, return_inverse=True)
                count = np.bincount(which, weight, minlength=len(made)).astype(np.int64)
                if dense is not None:
                    dense[made] += count
                    continue
                for k, c in zip(made.tolist(), count.tolist(), strict=True):
                    held[k] = held.get(k, 0) + c
                if len(held) > FLUSH:
                    yield out(np.asarray(list(held), np.int64), np.asarray(list(held.values()), np.int64))
                    held.clear()
        if dense is not None:
            key = np.flatnonzero(dense)
            yield out(key, dense[key])
        elif held:
            yield out(np.asarray(list(held), np.int64), np.asarray(list(held.values()), np.int64))

    return ranked.select("items", w.alias("weight")).mapInArrow(run, "hi int, lo int, n long").groupBy("hi", "lo").agg(F.sum("n").alias("pair_count"))


def pairs_by_join(long: DataFrame) -> DataFrame:
    """The same over rows (tid, item) as a self join: (item_a, item_b, pair_count) with item_a < item_b."""
    b = long.select("tid", F.col("item").alias("item_b"))
    both = long.select("tid", F.col("item").alias("item_a")).join(b, "tid").where("item_a < item_b")
    return both.groupBy("item_a", "item_b").agg(F.count(F.lit(1)).alias("pair_count"))
