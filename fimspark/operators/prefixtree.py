"""The prefix tree as a table: a node is a distinct prefix of a ranked row."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def prefix_key(prefix: Column, exact: bool) -> Column:
    """A prefix as a node's key: its hash, or the ranks themselves, for audits and small data."""
    return F.array_join(prefix, ",") if exact else F.xxhash64(prefix)


def exploded(ranked: DataFrame, exact: bool = False, *keep: str) -> DataFrame:
    """A row for each row's prefix: kept columns, node_key, parent_key, item_rank, depth, weight."""
    w = F.col("weight") if "weight" in ranked.columns else F.lit(1).cast("long")
    rows = ranked.select(*keep, w.alias("weight"), "items", F.posexplode("items").alias("p", "item_rank"))
    prefix = F.slice("items", F.lit(1), F.col("p") + 1)
    return rows.select(*keep, prefix_key(prefix, exact).alias("node_key"), prefix_key(F.slice("items", F.lit(1), F.col("p")), exact).alias("parent_key"), "item_rank", (F.col("p") + 1).alias("depth"), "weight")


def build(ranked: DataFrame, exact: bool = False) -> DataFrame:
    """(node_key, parent_key, item_rank, depth, node_count)."""
    rows = exploded(ranked, exact)
    return rows.groupBy("node_key").agg(F.first("parent_key").alias("parent_key"), F.first("item_rank").alias("item_rank"), F.first("depth").alias("depth"), F.sum("weight").alias("node_count"))


def count_nodes(ranked: DataFrame, exact: bool = False) -> DataFrame:
    """n_nodes as one row."""
    return exploded(ranked, exact).agg(F.count_distinct("node_key").alias("n_nodes"))
