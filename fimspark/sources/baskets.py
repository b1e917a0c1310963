"""Baskets (tid, items) of the workloads.

Null and empty items are dropped. A row left without items is a basket of no items where the source row exists, as each workload says.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .tables import table


def from_long(df: DataFrame, key: str = "tid", item: str = "item") -> DataFrame:
    """Rows (key, item) to baskets; repeated items of a basket count once."""
    rows = df.select(F.col(key).alias("tid"), F.col(item).cast("string").alias("item")).where("item is not null and item <> ''")
    return rows.groupBy("tid").agg(F.sort_array(F.collect_set("item")).alias("items"))


def to_long(tx: DataFrame) -> DataFrame:
    return tx.select("tid", F.explode("items").alias("item"))


def from_attributes(df: DataFrame, cols: dict[str, Column], tid: Column | None = None) -> DataFrame:
    """A basket of `name=value` items for each row; null values give no item."""
    items = F.array_compact(F.array(*(F.concat(F.lit(f"{n}="), c.cast("string")) for n, c in cols.items())))
    return df.select((F.monotonically_increasing_id() if tid is None else tid).alias("tid"), items.alias("items"))


def from_json(df: DataFrame, tid: str, col: str, path: str, prefix: str = "k=") -> DataFrame:
    value = F.get_json_object(col, path)
    return df.select(F.col(tid).alias("tid"), F.array_compact(F.array(F.concat(F.lit(prefix), value))).alias("items"))


def words(df: DataFrame, tid: str, text: str = "text") -> DataFrame:
    """The distinct words [a-z]+ of the lower-case text; a text without any is an empty basket."""
    tokens = F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), "[^a-z]+"), lambda x: x != "")
    return df.select(F.col(tid).alias("tid"), F.array_distinct(tokens).alias("items"))


def tags(pages: DataFrame) -> DataFrame:
    names = F.transform(F.regexp_extract_all("html", F.lit(r"<([a-zA-Z][a-zA-Z0-9]*)"), F.lit(1)), F.lower)
    return pages.select(F.col("page_id").alias("tid"), F.array_distinct(names).alias("items"))


def active_dims(emb: DataFrame, cut: float = 0.1) -> DataFrame:
    at = F.filter(F.transform("embedding", lambda v, i: F.when(v > cut, F.concat(F.lit("d"), i.cast("string")))), lambda x: x.isNotNull())
    return emb.select(F.col("vec_id").alias("tid"), at.alias("items"))


def labelled(tx: DataFrame, labels: DataFrame, key: str = "doc_id", cols: tuple[str, ...] = ("quality", "toxic")) -> DataFrame:
    """Baskets with `name=value` items of their labels added; baskets without labels are left out."""
    extra = F.array_compact(F.array(*(F.concat(F.lit(f"{c}="), F.col(c).cast("string")) for c in cols)))
    return tx.join(labels.select(F.col(key).alias("tid"), extra.alias("extra")), "tid").select("tid", F.array_union("items", "extra").alias("items"))


def order_brands(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W1: order -> brands of its parts. Baskets: orders with a line."""
    part = table(spark, sf_dir, "part", ["p_partkey", "p_brand"])
    return from_long(table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey"]).join(part, F.col("l_partkey") == F.col("p_partkey")), "l_orderkey", "p_brand")


def _customer_lines(spark: SparkSession, sf_dir: str, col: str) -> DataFrame:
    orders = table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"])
    return table(spark, sf_dir, "lineitem", ["l_orderkey", col]).join(orders, F.col("l_orderkey") == F.col("o_orderkey"))


def customer_brands(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W2: customer -> brands bought. Baskets: customers with a line."""
    part = table(spark, sf_dir, "part", ["p_partkey", "p_brand"])
    return from_long(_customer_lines(spark, sf_dir, "l_partkey").join(part, F.col("l_partkey") == F.col("p_partkey")), "o_custkey", "p_brand")


def part_suppliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W3: part -> suppliers."""
    return from_long(table(spark, sf_dir, "lineitem", ["l_partkey", "l_suppkey"]), "l_partkey", "l_suppkey")


def customer_suppliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W4: customer -> suppliers."""
    return from_long(_customer_lines(spark, sf_dir, "l_suppkey"), "o_custkey", "l_suppkey")


def document_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W5: document -> words. Baskets: all documents."""
    return words(table(spark, sf_dir, "documents", ["doc_id", "text"]), "doc_id")


def user_days(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W6: (user, day) -> event types; the tid is user * 100000 + day number."""
    e = table(spark, sf_dir, "events", ["user_id", "ts", "event_type"])
    return from_long(e.select((F.col("user_id") * 100000 + F.datediff(F.col("ts").cast("date"), F.lit("1970-01-01").cast("date"))).alias("k"), "event_type"), "k", "event_type")


def line_attributes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W7: lineitem row -> six attribute=value items. Baskets: rows, each with an id of its own."""
    return from_attributes(
        table(spark, sf_dir, "lineitem", ["l_returnflag", "l_linestatus", "l_quantity", "l_discount", "l_tax", "l_shipdate"]),
        {
            "flag": F.col("l_returnflag"),
            "status": F.col("l_linestatus"),
            "qty": F.floor(F.col("l_quantity") / 10).cast("int"),
            "disc": F.round(F.col("l_discount") * 100).cast("int"),
            "tax": F.round(F.col("l_tax") * 100).cast("int"),
            "year": F.year("l_shipdate"),
        },
    )


def page_tags(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W8: page -> html tags."""
    return tags(table(spark, sf_dir, "pages", ["page_id", "html"]))


def conversation_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W9: conversation -> words of all its turns."""
    turns = words(table(spark, sf_dir, "conversations", ["conv_id", "text"]), "conv_id")
    return from_long(to_long(turns))


def embedding_dims(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W10: embedding -> dimensions above 0.1."""
    return active_dims(table(spark, sf_dir, "embeddings", ["vec_id", "embedding"]))


WORKLOADS = {
    "w1": order_brands,
    "w2": customer_brands,
    "w3": part_suppliers,
    "w4": customer_suppliers,
    "w5": document_words,
    "w6": user_days,
    "w7": line_attributes,
    "w8": page_tags,
    "w9": conversation_words,
    "w10": embedding_dims,
}
