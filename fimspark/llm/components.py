"""Connected components of a link table, by rounds of joins.

Each round every node learns the least node among its neighbours and itself, and all its larger neighbours are linked
to that node instead; then the same towards the smaller ones. Links only move to smaller nodes and each component ends as a star, after a number of rounds
that grows with the logarithm of its diameter. Links are de-duplicated before each shuffle, so a node with very many links does not multiply them.
Each round is written to the shared checkpoint folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut


def components(links: DataFrame, rounds: int = 60) -> DataFrame:
    """links: a, b (longs). Returns node, component (the least node reachable) for each node that has a link to another."""
    e = cut(links.where("a <> b").select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).distinct())
    before = None
    for _ in range(rounds):
        # towards larger neighbours: both directions are needed to find the least
        both = e.select(F.col("hi").alias("u"), F.col("lo").alias("v")).unionByName(e.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("hi"), F.col("m").alias("lo")).where("hi <> lo").distinct()
        # towards smaller ones
        low = large.groupBy("hi").agg(F.min("lo").alias("m"))
        small = large.join(low, "hi").select(F.explode(F.array(F.struct(F.col("lo").alias("hi"), F.col("m").alias("lo")), F.struct("hi", F.col("m").alias("lo")))).alias("x")).select("x.hi", "x.lo").where("hi <> lo").distinct()
        e = cut(small)
        now = e.agg(F.count(F.lit(1)), F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)"))).first()
        if now == before:
            break
        before = now
    else:
        raise RuntimeError(f"links did not settle in {rounds} rounds")
    stars = e.select(F.col("hi").alias("node"), F.col("lo").alias("component"))
    return stars.unionByName(e.select(F.col("lo").alias("node"), F.col("lo").alias("component")).distinct())
