"""How good estimates, candidates and samples were."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.prefixtree import count_nodes
from .miner import MiningResult


def group_estimates(spark: SparkSession, result: MiningResult, capacity: int | None = None, planned: bool = False) -> DataFrame:
    """(group_id, lo, hi, est_nodes, real_nodes, ratio, utilisation): ratio is estimate over real size, so both kinds of error show.

    planned: only the groups of the plan for the table itself, without those that large ones were cut into, which have ids of their own.
    """
    rows = [
        (int(g["group_id"]), int(g["lo"]), int(g["hi"]), None if g["est_nodes"] is None else float(g["est_nodes"]), int(g["real_nodes"] or 0), g["how"])
        for g in result.groups
        if not planned or (g["how"] != "split" and not g.get("depth"))
    ]
    df = spark.createDataFrame(rows, "group_id long, lo int, hi int, est_nodes double, real_nodes long, how string")
    df = df.withColumn("ratio", F.round(F.try_divide("est_nodes", "real_nodes"), 6))
    return df.withColumn("utilisation", F.round(F.col("real_nodes") / F.lit(capacity), 6)) if capacity else df


def false_hits(candidates: DataFrame, fi: DataFrame) -> DataFrame:
    """One row: candidates, those that were not frequent, and their share."""
    c, f = candidates.count(), fi.count()
    return candidates.sparkSession.createDataFrame([(c, c - f, round((c - f) / c, 6) if c else 0.0)], "candidates long, false_hits long, share double")


def recall(found: DataFrame, exact: DataFrame) -> DataFrame:
    """One row: sets in the exact answer, those missed, and recall."""
    n = exact.agg(F.count(F.lit(1)).alias("n"))
    missed = exact.select("itemset").exceptAll(found.select("itemset")).agg(F.count(F.lit(1)).alias("missed"))
    return n.crossJoin(missed).select("n", "missed", F.round(F.when(F.col("n") > 0, (F.col("n") - F.col("missed")) / F.col("n")).otherwise(1.0), 6).alias("recall"))


def compression(ranked: DataFrame, exact: bool = False) -> DataFrame:
    """One row: items in the ranked rows, nodes of their tree, and nodes over items."""
    cells = ranked.agg(F.coalesce(F.sum(F.size("items")), F.lit(0)).cast("long").alias("cells"))
    return cells.crossJoin(count_nodes(ranked, exact)).select("cells", "n_nodes", F.round(F.when(F.col("cells") > 0, F.col("n_nodes") / F.col("cells")).otherwise(0.0), 6).alias("ratio"))
