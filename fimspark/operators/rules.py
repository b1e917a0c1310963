"""Association rules from frequent sets, and sets that stand for others."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


#: Bits of a mask that one array enumerates.
HALF = 12


def _parts() -> tuple:
    return F.split("itemset", r"\|")


def generate(fi: DataFrame, n_tx: int, min_conf: float) -> DataFrame:
    """Rules antecedent -> consequent of all splits of each set; every antecedent and consequent is itself in fi.

    A set of size s has 2**s - 2 splits, all between sets of fi; they are enumerated by bit masks, HALF bits at a time, so that no row holds more than 2**HALF of them, and joined to their
    supports by equality.
    """
    sets = fi.where("size >= 2").select("itemset", "support_count", "size", _parts().alias("p"))
    high = sets.select("*", F.explode(F.expr(f"sequence(0L, shiftleft(1L, greatest(size - {HALF}, 0)) - 1)")).alias("high"))
    masks = high.select("*", F.explode(F.expr(f"transform(sequence(0L, shiftleft(1L, least(size, {HALF})) - 1), x -> shiftleft(high, {HALF}) | x)")).alias("m")).where("m > 0 AND m < shiftleft(1L, size) - 1")
    side = lambda want: F.array_join(F.filter("p", lambda x, i: F.expr("1L").bitwiseAND(F.call_function("shiftright", F.col("m"), i)) == want), "|")
    splits = masks.select("itemset", "support_count", side(1).alias("antecedent"), side(0).alias("consequent"))
    a = fi.select(F.col("itemset").alias("antecedent"), F.col("support_count").alias("a_count"))
    c = fi.select(F.col("itemset").alias("consequent"), F.col("support_count").alias("c_count"))
    r = splits.join(a, "antecedent").where(F.col("support_count") >= min_conf * F.col("a_count") - 1e-9).join(c, "consequent")
    n = F.lit(float(n_tx))
    conf, support_c = F.col("support_count") / F.col("a_count"), F.col("c_count") / n
    return r.select(
        "antecedent",
        "consequent",
        "support_count",
        F.round(conf, 6).alias("confidence"),
        F.round(F.col("support_count") * n / (F.col("a_count") * F.col("c_count")), 6).alias("lift"),
        F.round(F.col("support_count") / n - F.col("a_count") / n * F.col("c_count") / n, 6).alias("leverage"),
        F.round(F.when(F.col("support_count") < F.col("a_count"), (1 - support_c) / (1 - conf)), 6).alias("conviction"),
    )


def _best_superset(fi: DataFrame) -> DataFrame:
    """itemset -> largest support of a frequent set with one item more."""
    s = fi.where("size >= 2").select("support_count", _parts().alias("p"))
    one_less = s.select("support_count", F.explode(F.transform("p", lambda x, i: F.array_join(F.filter("p", lambda y, j: j != i), "|"))).alias("itemset"))
    return one_less.groupBy("itemset").agg(F.max("support_count").alias("best"))


def closed(fi: DataFrame) -> DataFrame:
    """Sets with no superset of equal support; over the whole answer, since a set that looks closed in one projected database may not be in another."""
    return fi.join(_best_superset(fi), "itemset", "left").where("best IS NULL OR best < support_count").select("itemset", "size", "support_count")


def maximal(fi: DataFrame) -> DataFrame:
    """Sets with no frequent superset."""
    return fi.join(_best_superset(fi).select("itemset"), "itemset", "left_anti").select("itemset", "size", "support_count")


def topk(fi: DataFrame, k: int) -> DataFrame:
    return fi.orderBy(F.desc("support_count"), "size", "itemset").limit(k)


def diff_runs(a: DataFrame, b: DataFrame) -> DataFrame:
    """(itemset, count_a, count_b): full outer comparison of two answers; null where a run has not the set."""
    return a.select("itemset", F.col("support_count").alias("count_a")).join(b.select("itemset", F.col("support_count").alias("count_b")), "itemset", "full")


def where_items(df: DataFrame, col: str, all: list[str] | None = None, any: list[str] | None = None, none: list[str] | None = None) -> DataFrame:  # noqa: A002
    """Rows whose item array has all, any or none of some items."""
    for want, test in ((all, lambda x: F.forall(F.lit(x), lambda v: F.array_contains(col, v))), (any, lambda x: F.arrays_overlap(col, F.lit(x))), (none, lambda x: ~F.arrays_overlap(col, F.lit(x)))):
        if want:
            df = df.where(test(want))
    return df
