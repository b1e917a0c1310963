"""What SQL users call: a table function that mines, a tree-size aggregate, a subset test, and views."""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators.localmine import Rows, mine_all, node_count


@F.udtf(returnType="itemset string, size int, support_count long")
class FrequentItemsets:
    """frequent_itemsets(TABLE(baskets) PARTITION BY key, min_count): the frequent sets of each partition's baskets; column items holds a basket."""

    def __init__(self):
        self.rows, self.min_count = [], 1

    def eval(self, row, min_count: int):
        self.rows.append(list(row["items"] or []))
        self.min_count = min_count

    def terminate(self):
        counts: dict[str, int] = {}
        for r in self.rows:
            for i in set(r):
                counts[i] = counts.get(i, 0) + 1
        names = sorted((i for i, c in counts.items() if c >= self.min_count), key=lambda i: (-counts[i], i))
        rank = {i: k + 1 for k, i in enumerate(names)}
        lists = [sorted({rank[i] for i in r if i in rank}) for r in self.rows]
        for s, c in mine_all(Rows.of(lists), self.min_count):
            yield "|".join(sorted(names[k - 1] for k in s)), len(s), c


@F.pandas_udf(T.LongType())
def tree_size(items: pd.Series) -> int:
    """Aggregate: nodes of the prefix tree of a group's ranked rows."""
    return node_count(Rows.of([list(x) for x in items]))


@F.arrow_udf(T.BooleanType())
def is_subset(items: pa.Array, candidate: pa.Array) -> pa.Array:
    return pa.array([None if a is None or c is None else set(c) <= set(a) for a, c in zip(items.to_pylist(), candidate.to_pylist(), strict=True)], pa.bool_())


def register(spark: SparkSession, fi: DataFrame | None = None, pairs: DataFrame | None = None, items: DataFrame | None = None) -> None:
    spark.udtf.register("frequent_itemsets", FrequentItemsets)
    spark.udf.register("tree_size", tree_size)
    for name, df in {"fi": fi, "pairs": pairs, "items": items}.items():
        if df is not None:
            df.createOrReplaceTempView(name)


class BudgetedItemsetMiner:
    """fit/transform facade: fit mines, transform adds the consequents of rules whose antecedents a basket holds."""

    def __init__(self, min_support: float = 0.01, node_budget: int = 1_000_000, min_confidence: float = 0.8, **options):
        self.min_support, self.node_budget, self.min_confidence, self.options = min_support, node_budget, min_confidence, options

    def fit(self, tx: DataFrame) -> BudgetedItemsetMiner:
        from ..operators.rules import generate
        from ..plans.miner import mine_budgeted

        self.result = mine_budgeted(tx, self.min_support, self.node_budget, **self.options)
        self.freq_itemsets = self.result.fi
        self.association_rules = generate(self.result.fi, tx.count(), self.min_confidence)
        return self

    def transform(self, tx: DataFrame) -> DataFrame:
        """Rules meet baskets by one item of the antecedent (its first), then the whole antecedent is tested."""
        r = self.association_rules.select(F.split("antecedent", r"\|").alias("a"), F.split("consequent", r"\|").alias("c")).withColumn("item", F.element_at("a", 1))
        long = tx.select("tid", "items", F.explode("items").alias("item"))
        hit = long.join(r, "item").where(F.size(F.array_except("a", "items")) == 0).select("tid", F.explode(F.array_except("c", "items")).alias("x"))
        return tx.join(hit.groupBy("tid").agg(F.array_sort(F.collect_set("x")).alias("prediction")), "tid", "left").select("tid", "items", F.coalesce("prediction", F.array().cast("array<string>")).alias("prediction"))
