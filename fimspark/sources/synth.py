"""Synthetic baskets: pattern pools with hash-seeded draws, so any row can be made anywhere and always the same.

A basket draws patterns from a pool until its length is reached; pattern lengths and basket lengths spread around their means. Draws favour patterns and items of low
number (squares of uniform draws), which gives the long tail of real baskets.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def baskets(spark: SparkSession, n_tx: int, n_items: int, avg_len: int = 10, avg_pattern: int = 4, n_patterns: int = 200, seed: int = 42, corruption: float = 0.0) -> DataFrame:
    """corruption: the share of a pattern's items that a draw leaves out, each by a draw of its own."""
    u = lambda *c: F.pmod(F.xxhash64(F.lit(seed), *c), F.lit(1_000_003)) / 1_000_003.0
    square = lambda x: x * x
    need = F.greatest(F.lit(1), F.round(avg_len * (0.5 + u(F.col("id"), F.lit("len")))).cast("int"))
    n_draws = F.greatest(F.lit(1), F.ceil(F.col("need") / (avg_pattern * (1 - corruption))).cast("int"))
    pattern = lambda d: F.floor(n_patterns * square(u(F.col("id"), d, F.lit("p"))))
    item = lambda p, k: F.floor(n_items * square(u(p, k, F.lit("i"))))
    rows = spark.range(n_tx).withColumn("need", need)
    kept = (lambda d, k: F.when(u(F.col("id"), d, k, F.lit("c")) >= corruption, item(pattern(d), k))) if corruption else lambda d, k: item(pattern(d), k)
    drawn = F.array_compact(F.flatten(F.transform(F.sequence(F.lit(1), n_draws), lambda d: F.transform(F.sequence(F.lit(1), F.lit(avg_pattern)), lambda k: kept(d, k)))))
    items = F.transform(F.slice(F.array_distinct(drawn), F.lit(1), F.col("need")), lambda i: F.concat(F.lit("i"), i.cast("string")))
    return rows.select(F.col("id").alias("tid"), items.alias("items"))


class SyntheticBasketSource(DataSource):
    """spark.read.format("synthetic_baskets") with options n_tx, n_items, avg_len, avg_pattern, n_patterns, seed and partitions.

    The same law as baskets(), with the random numbers of the library seeded by row, for users who want a format instead of a function.
    """

    @classmethod
    def name(cls) -> str:
        return "synthetic_baskets"

    def schema(self) -> str:
        return "tid long, items array<string>"

    def reader(self, schema) -> DataSourceReader:
        return _Reader({k.lower(): v for k, v in self.options.items()})


class _Reader(DataSourceReader):
    DEFAULTS = {"n_tx": 1000, "n_items": 1000, "avg_len": 10, "avg_pattern": 4, "n_patterns": 200, "seed": 42, "partitions": 8}

    def __init__(self, options: dict):
        self.options = {k: int(options.get(k, v)) for k, v in self.DEFAULTS.items()}

    def partitions(self) -> list[InputPartition]:
        n, p = self.options["n_tx"], self.options["partitions"]
        return [InputPartition((n * k // p, n * (k + 1) // p)) for k in range(p)]

    def read(self, partition):
        import random

        o = self.options
        lo, hi = partition.value
        for tid in range(lo, hi):
            rng = random.Random(o["seed"] * 1_000_003 + tid)
            need, items = max(1, round(o["avg_len"] * (0.5 + rng.random()))), []
            while len(items) < need:
                pattern = random.Random(f"{o['seed']}/{int(o['n_patterns'] * rng.random() ** 2)}")
                items += [x for x in (f"i{int(o['n_items'] * pattern.random() ** 2)}" for _ in range(o["avg_pattern"])) if x not in items]
                need -= 0 if rng.random() < 0.9 else 1
            yield (tid, items[: max(1, need)])
