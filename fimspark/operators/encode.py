"""Item counts, the frequency order, and baskets as sorted ranks.

Rank 1 is the most frequent item; ties are broken by the item's bytes. Ranked rows hold ranks in rising order, so a cut to the ranks up to any
bound is a prefix, and equal rows can be collapsed into one with a weight.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: A dictionary with more items is joined instead of sent to all tasks.
MAX_SENT_ITEMS = 1_000_000


def resolve_min_count(tx: DataFrame | int, min_support: float | int, strict: bool = False) -> int:
    """Absolute threshold, at least 1. A float below 1 is a share of all baskets; strict asks for more than the share."""
    if isinstance(min_support, float) and min_support <= 1:
        n = tx if isinstance(tx, int) else tx.count()
        x = min_support * n
        return max(1, math.floor(x + 1e-9) + 1 if strict else math.ceil(x - 1e-9))
    return max(1, int(min_support) + int(strict))


def count_items(tx: DataFrame) -> DataFrame:
    return tx.select(F.explode("items").alias("item")).groupBy("item").agg(F.count(F.lit(1)).alias("item_count"))


def count_items_and_rows(tx: DataFrame) -> DataFrame:
    """The same with one row more, of item null: the number of baskets. Both come from one scan."""
    item = F.explode(F.concat(F.array(F.lit(None).cast("string")), F.coalesce("items", F.array().cast("array<string>"))))
    return tx.select(item.alias("item")).groupBy("item").agg(F.count(F.lit(1)).alias("item_count"))


def frequency_order(counts: DataFrame, min_count: int) -> DataFrame:
    """(item, item_rank, item_count); the window sees the frequent items only."""
    by = Window.orderBy(F.desc("item_count"), "item")
    return counts.where(F.col("item_count") >= min_count).select("item", F.row_number().over(by).alias("item_rank"), "item_count")


def _sorted_lists(row: np.ndarray, rank: np.ndarray, n_rows: int) -> pa.ListArray:
    key = np.lexsort((rank, row))
    offsets = np.searchsorted(row[key], np.arange(n_rows + 1))
    return pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(rank[key], pa.int32()))


def sendable_names(order: DataFrame) -> list[str] | None:
    """The items by rank, or None if they are too many to send to all tasks."""
    rows = order.select("item_rank", "item").limit(MAX_SENT_ITEMS + 1).toArrow()
    if rows.num_rows > MAX_SENT_ITEMS:
        return None
    return [i for _, i in sorted(zip(rows["item_rank"].to_pylist(), rows["item"].to_pylist(), strict=True))]


def rank_transactions(tx: DataFrame, order: DataFrame, names: list[str] | None = None) -> DataFrame:
    """(tid, items): ranks of the frequent items of each basket, rising; infrequent ones go. Baskets may become empty.

    names: the items by rank, if the caller has them.
    """
    names = sendable_names(order) if names is None else names
    if names is None:
        long = tx.select("tid", F.explode("items").alias("item")).join(order.select("item", "item_rank"), "item")
        lists = long.groupBy("tid").agg(F.array_sort(F.collect_list("item_rank")).alias("ranked"))
        return tx.select("tid").join(lists, "tid", "left").select("tid", F.coalesce("ranked", F.array().cast("array<int>")).alias("items"))
    sent = tx.sparkSession.sparkContext.broadcast(pa.array(names, pa.string()))  # MAX_SENT_ITEMS at most

    def run(batches):
        names = sent.value
        for b in batches:
            lists = b.column(1)
            flat = pc.list_flatten(lists)
            row = pc.list_parent_indices(lists).to_numpy(zero_copy_only=False).astype(np.int64)
            rank = pc.index_in(flat, value_set=names)
            ok = rank.is_valid().to_numpy(zero_copy_only=False)
            ranks = rank.fill_null(-1).to_numpy(zero_copy_only=False)[ok].astype(np.int32) + 1
            yield pa.RecordBatch.from_arrays([b.column(0), _sorted_lists(row[ok], ranks, b.num_rows)], names=["tid", "items"])

    return tx.select(F.col("tid").cast("long").alias("tid"), "items").mapInArrow(run, "tid long, items array<int>")


def collapse(ranked: DataFrame, *keys: str) -> DataFrame:
    """Equal rows as one with their total weight (map-side combined); empty rows go."""
    w = F.col("weight") if "weight" in ranked.columns else F.lit(1).cast("long")
    return ranked.where(F.size("items") > 0).groupBy(*keys, "items").agg(F.sum(w).alias("weight"))


def decode(fi: DataFrame, order: DataFrame, names: list[str] | None = None) -> DataFrame:
    """(itemset ARRAY<INT>, support_count) to (itemset STRING, size, support_count): items in byte order joined by `|`."""
    names = sendable_names(order) if names is None else names
    if names is None:
        long = fi.select("itemset", "support_count", F.explode("itemset").alias("item_rank")).join(order.select("item", "item_rank"), "item_rank")
        return long.groupBy("itemset", "support_count").agg(F.collect_list("item").alias("names")).select(F.array_join(F.array_sort("names"), "|").alias("itemset"), F.size("names").alias("size"), "support_count")
    sent = fi.sparkSession.sparkContext.broadcast(names)  # MAX_SENT_ITEMS at most

    def run(batches):
        for b in batches:
            text = ["|".join(sorted((sent.value[r - 1] for r in x), key=lambda s: s.encode())) for x in b.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(text, pa.string()), pc.list_value_length(b.column(0)).cast(pa.int32()), b.column(1)], names=["itemset", "size", "support_count"])

    return fi.select("itemset", "support_count").mapInArrow(run, "itemset string, size int, support_count long")
