"""The two ways to take a database apart."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import project
from .grouping import Group


def by_partition(tx: DataFrame, cells: int, by: str = "hash") -> DataFrame:
    """Disjoint cells by a hash of the tid (by = "hash") or by the tid itself (by = "tid"). What is frequent in a cell is a candidate only and has to be counted over everything."""
    return tx.withColumn("cell", F.pmod(F.xxhash64("tid") if by == "hash" else F.col("tid"), F.lit(cells)))


def by_projection(txw: DataFrame, groups: list[Group], n: int) -> DataFrame:
    """Overlapping projected databases, one for each group of anchors. Their answers are answers, and are put together by union."""
    return project.by_group(txw, groups, n)
