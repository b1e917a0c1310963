"""Relational views that users need around mining: profiles, popularity, joins in time, moving baskets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def join_equi(a: DataFrame, b: DataFrame, on: Column, hint: str | None = None) -> DataFrame:
    """Inner join; hint: broadcast, merge, shuffle_hash or shuffle_replicate_nl. Without one the optimiser decides by size."""
    return a.join(b.hint(hint) if hint else b, on)


#: Keys of the right side in a block, and partitions of blocks on each side, which a nested loop pairs with each other.
BLOCK_KEYS, BLOCK_PARTS = 1000, 8


def join_blocks(a: DataFrame, b: DataFrame, left: str, right: str, hint: str = "shuffle_replicate_nl") -> DataFrame:
    """Inner join by a.left = b.right whose hinted join pairs blocks of rows; the columns of both, whose names differ.

    A block has the rows whose keys hash alike, so rows meet in equal blocks only. There are so many that b has BLOCK_KEYS keys in each, on average: a nested loop then makes a pair for
    any two blocks, and not for any two rows. A block's rows are an array, so a key with very many rows should be aggregated before.
    """
    b = b.where(F.col(right).isNotNull()).groupBy(right).agg(F.collect_list(F.struct(*(c for c in b.columns if c != right))).alias("_same"))
    n = max(1, -(-b.count() // BLOCK_KEYS))

    def blocks(df: DataFrame, key: str, name: str, rows: Column) -> DataFrame:
        return df.groupBy(F.pmod(F.xxhash64(F.col(key).cast("string")), F.lit(n)).alias(name)).agg(rows.alias(f"{name}_rows")).coalesce(BLOCK_PARTS)

    x = blocks(a.where(F.col(left).isNotNull()), left, "_a", F.collect_list(F.struct(*a.columns)))
    y = blocks(b, right, "_b", F.map_from_entries(F.collect_list(F.struct(right, "_same"))))
    met = x.join(y.hint(hint), F.col("_a") == F.col("_b"))
    pairs = met.select("_b_rows", F.explode("_a_rows").alias("_x")).select("_x", F.explode(F.try_element_at("_b_rows", F.col(f"_x.{left}"))).alias("_y"))
    return pairs.select("_x.*", F.col(f"_x.{left}").alias(right), "_y.*")


def keep_frequent(tx: DataFrame, order: DataFrame) -> DataFrame:
    """(tid, item) of frequent items only."""
    return tx.select("tid", F.explode("items").alias("item")).join(order.select("item"), "item", "left_semi").select("tid", "item")


def restrict(tx: DataFrame, given: list[str]) -> DataFrame:
    """The baskets that hold all given items, without them."""
    has = F.forall(F.lit(given), lambda v: F.array_contains("items", v))
    return tx.where(has).select("tid", F.array_except("items", F.lit(given)).alias("items"))


def zero_filled_pairs(pairs: DataFrame, items: DataFrame) -> DataFrame:
    """All pairs item_a < item_b with 0 where they never meet; for small dictionaries, whose square is the size of the answer."""
    a, b = items.select(F.col("item").alias("item_a")), items.select(F.col("item").alias("item_b"))
    return a.crossJoin(b).where("item_a < item_b").join(pairs, ["item_a", "item_b"], "left").select("item_a", "item_b", F.coalesce("pair_count", F.lit(0)).cast("long").alias("pair_count"))


def rank_to_group(order: DataFrame, groups: DataFrame) -> DataFrame:
    """Each item's group by its rank's range; groups is the planner's small table."""
    g = groups.select("group_id", "lo", "hi")
    return order.join(F.broadcast(g), (F.col("item_rank") >= F.col("lo")) & (F.col("item_rank") <= F.col("hi"))).select("item", "item_rank", "group_id")


def asof(left: DataFrame, right: DataFrame, by: str, ts: str, value: str, out: str) -> DataFrame:
    """Each left row with the value of the latest right row of its key that is earlier, by one pass over both sorted by time.

    Both sides are stacked and a running last value is taken, so that a key's rows are sorted once and never paired.
    """
    cols = left.columns
    a = left.select(*cols, F.lit(None).cast(dict(right.dtypes)[value]).alias("_v"), F.lit(1).alias("_side"))
    b = right.select(*(F.col(c) if c in (by, ts) else F.lit(None).cast(dict(left.dtypes)[c]).alias(c) for c in cols), F.col(value).alias("_v"), F.lit(2).alias("_side"))
    w = Window.partitionBy(by).orderBy(ts, "_side").rowsBetween(Window.unboundedPreceding, -1)  # equal times: left first, so only earlier ones count
    return a.unionByName(b).withColumn(out, F.last("_v", ignorenulls=True).over(w)).where("_side = 1").select(*cols, out)


def interval_pairs(events: DataFrame, seconds: int) -> DataFrame:
    """(type_a, type_b, n): pairs of types of events of one user at most so many seconds apart, each unordered pair of events once.

    Time is cut in slots of that length, so an event meets its own slot and the one after only.
    """
    e = events.select("user_id", "event_id", F.col("event_type").alias("t"), F.unix_micros(F.col("ts").cast("timestamp")).alias("u"))
    span = seconds * 1_000_000
    slot = F.floor(F.col("u") / span)
    a = e.select("user_id", F.col("event_id").alias("ea"), F.col("t").alias("ta"), F.col("u").alias("ua"), F.explode(F.array(slot, slot + 1)).alias("s"))
    b = e.select("user_id", F.col("event_id").alias("eb"), F.col("t").alias("tb"), F.col("u").alias("ub"), slot.alias("s"))
    later = (F.col("ub") > F.col("ua")) | ((F.col("ub") == F.col("ua")) & (F.col("eb") > F.col("ea")))
    both = a.join(b, ["user_id", "s"]).where(later & (F.col("ub") - F.col("ua") <= span))
    return both.groupBy(F.least("ta", "tb").alias("type_a"), F.greatest("ta", "tb").alias("type_b")).agg(F.count(F.lit(1)).alias("n"))


def moving_basket(events: DataFrame, seconds: int) -> DataFrame:
    """Each event with the distinct types of its user within so many seconds before it, itself included."""
    u = F.unix_seconds(F.col("ts").cast("timestamp"))
    w = Window.partitionBy("user_id").orderBy(F.col("u")).rangeBetween(-seconds, 0)
    return events.withColumn("u", u).select("event_id", F.array_join(F.array_sort(F.collect_set("event_type").over(w)), "|").alias("basket"))


def session_baskets(events: DataFrame, gap_seconds: int) -> DataFrame:
    """(user_id, session_start, items): events closer than the gap to the one before are one session."""
    u = F.unix_micros(F.col("ts").cast("timestamp"))
    w = Window.partitionBy("user_id").orderBy("u")
    new = F.when(F.col("u") - F.lag("u").over(w) < gap_seconds * 1_000_000, 0).otherwise(1)
    rows = events.select("user_id", "event_type", u.alias("u")).withColumn("new", new).withColumn("s", F.sum("new").over(w))
    return rows.groupBy("user_id", "s").agg(F.min("u").alias("start_us"), F.array_join(F.array_sort(F.collect_set("event_type")), "|").alias("basket")).select("user_id", "start_us", "basket")


def basket_profile(tx: DataFrame) -> DataFrame:
    n = F.size("items")
    return tx.agg(F.count(F.lit(1)).alias("baskets"), F.round(F.avg(n), 6).alias("mean_len"), F.max(n).cast("long").alias("max_len"), F.round(F.percentile(n, 0.5), 6).alias("median_len"))


def approx_rows(tx: DataFrame) -> DataFrame:
    return tx.agg(F.approx_count_distinct(F.xxhash64("items")).alias("rows"))


def attr_supports(df: DataFrame, cols: list[str], mode: str = "cube") -> DataFrame:
    """Counts of all combinations of attribute values; absent attributes are null."""
    return getattr(df, mode)(*cols).agg(F.count(F.lit(1)).alias("support_count"))


def popularity(counts: DataFrame) -> DataFrame:
    w = Window.orderBy(F.desc("item_count"))
    return counts.select("item", "item_count", F.rank().over(w).alias("rank"), F.dense_rank().over(w).alias("dense_rank"), F.round(F.percent_rank().over(w), 6).alias("percent_rank"), F.round(F.cume_dist().over(w), 6).alias("cume_dist"))


def count_gaps(order: DataFrame) -> DataFrame:
    w = Window.orderBy("item_rank")
    return order.select("item", "item_rank", (F.lag("item_count").over(w) - F.col("item_count")).alias("gap"))


def topk_partners(pairs: DataFrame, k: int) -> DataFrame:
    """The k most frequent partners of each item. pairs: item_a, item_b, pair_count."""
    both = pairs.select(F.col("item_a").alias("item"), F.col("item_b").alias("partner"), "pair_count").unionByName(pairs.select(F.col("item_b").alias("item"), F.col("item_a").alias("partner"), "pair_count"))
    w = Window.partitionBy("item").orderBy(F.desc("pair_count"), "partner")
    return both.withColumn("place", F.row_number().over(w)).where(F.col("place") <= k)


def mask(items: Column, names: list[str]) -> Column:
    """A basket over at most 63 items as bits of a long: item number k of names is bit k."""
    out = F.lit(0).cast("long")
    for k, name in enumerate(names):
        out = out.bitwiseOR(F.when(F.array_contains(items, name), F.lit(1 << k).cast("long")).otherwise(F.lit(0).cast("long")))
    return out


def calendar_items(ts: Column) -> Column:
    return F.array(F.concat(F.lit("year="), F.year(ts)), F.concat(F.lit("month="), F.month(ts)), F.concat(F.lit("dow="), F.dayofweek(ts)))
