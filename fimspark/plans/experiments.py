"""The published experiments on the given tables: which method moves how much, and how estimates and times go with the parameters."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import project
from ..session import stage
from . import baselines, miner
from .ledger import CostLedger

COLUMNS = "workload string, share double, method string, itemsets long, groups long, moved_cells long, seconds double"
#: The budgeted miner's techniques, each turned off or exchanged.
VARIANTS = {
    "all": {},
    "no array": {"array": False},
    "no pruning": {"prune": False},
    "head projected": {"bypass_head": False},
    "pilot read again": {"reuse_pilot": False},
    "cut by ratio": {"cut": "ratio"},
    "cut by trimmed size": {"cut": "nu"},
    "packed by union": {"packing": "union"},
    "trees apart": {"shared_tree": False},
}


def _sent(r: miner.MiningResult) -> int:
    """Cells of projected databases that were written or sent."""
    return sum(r.ledger.cells(p) for p in ("head", "projected", "projected again"))


def compare(spark: SparkSession, tx: DataFrame, workload: str, shares: list[float], node_budget: int, cells: int = 4) -> DataFrame:
    """For each share: grouped projection, per-item projection and partitioning.

    moved_cells are items of projected databases, or candidates, that go between stages. Collapsing is the same for both projections. The pilot takes rows, and
    cells of the partitioned method are dealt, by the baskets' numbers, so that the same table gives the same figures anywhere.
    """
    tx = stage(tx)
    rows = []
    for share in shares:
        began = time.perf_counter()
        r = miner.mine_budgeted(tx, share, node_budget, order="tid", measure=True)
        rows.append((workload, share, "grouped", r.fi.count(), len(r.groups), _sent(r), time.perf_counter() - began))
        began = time.perf_counter()
        r = miner.mine_per_item(tx, share, measure=True)
        rows.append((workload, share, "per item", r.fi.count(), len(r.groups), _sent(r), time.perf_counter() - began))
        began = time.perf_counter()
        r = baselines.partitioned(tx, share, cells, ledger=CostLedger(), by="tid")
        rows.append((workload, share, "partitioned", r.fi.count(), cells, r.ledger.cells("candidates"), time.perf_counter() - began))
    return spark.createDataFrame(rows, COLUMNS)


def ablation(spark: SparkSession, tx: DataFrame, workload: str, share: float, node_budget: int) -> DataFrame:
    """The budgeted miner with each of its techniques turned off or exchanged. written_cells: all that goes between stages, moved_cells: projected databases alone."""
    tx = stage(tx)
    rows = []
    for name, options in VARIANTS.items():
        began = time.perf_counter()
        r = miner.mine_budgeted(tx, share, node_budget, order="tid", measure=True, **options)
        rows.append((workload, name, r.fi.count(), len(r.groups), _sent(r), r.ledger.written(), r.counters.traversals, r.counters.trees, time.perf_counter() - began))
    return spark.createDataFrame(rows, "workload string, variant string, itemsets long, groups long, moved_cells long, written_cells long, traversals long, trees long, seconds double")


def volume_by_groups(spark: SparkSession, ranked: DataFrame, n: int, ks: list[int]) -> DataFrame:
    """Cells of projected databases, not collapsed, for k equal groups, beside (k + 1) / 2 copies of the source."""
    from .grouping import equal_groups

    rows = stage(ranked.select("items", F.lit(1).cast("long").alias("weight")))
    source = rows.agg(F.coalesce(F.sum(F.size("items")), F.lit(0))).first()[0]
    out = []
    for k in ks:
        proj = project.by_group(rows, equal_groups(n, k), n)
        cells = proj.agg(F.coalesce(F.sum(F.size("items") * F.col("weight")), F.lit(0))).first()[0]
        out.append((k, source, cells, cells / source if source else 0.0, (min(k, n) + 1) / 2))
    return spark.createDataFrame(out, "k int, source_cells long, projected_cells long, expansion double, formula double")


__all__ = ["ablation", "compare", "volume_by_groups"]
