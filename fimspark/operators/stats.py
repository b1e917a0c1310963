"""Statistics of a database and its pilot tree, as tables and for the planner."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .pilot import Pilot
from .prefixtree import exploded, prefix_key


def nu_trimmed(rows: DataFrame, exact: bool = False) -> DataFrame:
    """(item_rank, nu): nodes of the tree cut to ranks up to item_rank. rows has items."""
    per = exploded(rows, exact).groupBy("item_rank").agg(F.count_distinct("node_key").alias("n"))
    return per.select("item_rank", F.sum("n").over(Window.orderBy("item_rank").rowsBetween(Window.unboundedPreceding, 0)).alias("nu"))


def mu_anchor(rows: DataFrame, pairs: DataFrame, min_count: int, exact: bool = False, include_anchor: bool = False) -> DataFrame:
    """(item_rank, mu): nodes on a branch through item_rank, of items before it that are frequent with it; items without any are left out."""
    w = rows.select("items", F.posexplode("items").alias("pj", "item_rank"))
    both = w.select("item_rank", F.explode(F.transform(F.slice("items", F.lit(1), F.col("pj")), lambda x, i: F.struct(x.alias("lo"), prefix_key(F.slice("items", F.lit(1), i + 1), exact).alias("node")))).alias("q")).select("item_rank", "q.lo", "q.node")
    frequent = pairs.where(F.col("pair_count") >= min_count).select(F.col("hi").alias("item_rank"), "lo")
    nodes = both.join(frequent, ["item_rank", "lo"], "left_semi").select("item_rank", "node")
    if include_anchor:
        nodes = nodes.unionByName(exploded(rows, exact).select("item_rank", F.col("node_key").alias("node")))
    return nodes.groupBy("item_rank").agg(F.count_distinct("node").alias("mu"))


@dataclass
class StatsBundle:
    """What the planner reads: everything by rank is indexed from 1 (index 0 is unused)."""

    n: int
    n_total: int
    n_used: int
    nodes: int
    nu: np.ndarray
    mu: np.ndarray
    scale: float


def collect_stats(pilot: Pilot, pairs: DataFrame, n: int, min_count: int, exact: bool = False) -> StatsBundle:
    """One row for each frequent item comes to the driver."""
    nu, mu = np.zeros(n + 1, np.int64), np.zeros(n + 1, np.int64)
    for r in exploded(pilot.rows, exact).groupBy("item_rank").agg(F.count_distinct("node_key").alias("c")).collect():
        nu[r["item_rank"]] = r["c"]
    for r in mu_anchor(pilot.rows, pairs, min_count, exact).collect():
        mu[r["item_rank"]] = r["mu"]
    return StatsBundle(n, pilot.n_total, pilot.n_used, pilot.nodes, np.cumsum(nu), mu, pilot.scale)
