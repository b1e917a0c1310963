"""Tables in Parquet, and files of baskets in other formats."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str, cols: list[str] | None = None, where: str | Column | None = None) -> DataFrame:
    """Only the named columns and rows are read: both reach the Parquet scan."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if where is not None:
        df = df.where(where)
    return df.select(*cols) if cols else df


def read_baskets(spark: SparkSession, path: str, fmt: str = "text") -> DataFrame:
    """(tid, items): text has a row's items with spaces between; csv has tid,item lines; json and orc have tid and items.

    Text has no tid: rows get ids that are unique but not consecutive.
    """
    if fmt == "text":
        lines = spark.read.text(path)
        items = F.array_distinct(F.filter(F.split("value", r"\s+"), lambda x: x != ""))
        return lines.select(F.monotonically_increasing_id().alias("tid"), items.alias("items"))
    if fmt == "csv":
        from .baskets import from_long

        return from_long(spark.read.schema("tid long, item string").csv(path))
    return spark.read.schema("tid long, items array<string>").format(fmt).load(path)


def write_baskets(tx: DataFrame, path: str, fmt: str = "text") -> None:
    if fmt == "text":
        tx.select(F.array_join("items", " ").alias("value")).write.mode("overwrite").text(path)
    elif fmt == "csv":
        tx.select("tid", F.explode("items").alias("item")).write.mode("overwrite").csv(path)
    else:
        tx.select("tid", "items").write.mode("overwrite").format(fmt).save(path)


def write_itemsets(fi: DataFrame, path: str) -> None:
    """Results by size, so that a reader of one size reads only its files."""
    fi.write.mode("overwrite").partitionBy("size").parquet(path)
