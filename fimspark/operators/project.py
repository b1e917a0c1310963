"""Projected databases: all groups of a level in one table.

A row goes to each group of which it has an anchor, cut to the group's last rank and, with pair counts, without items that are of no use there.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.grouping import Group

LIST_LIMIT = 1 << 20


def per_item(txw: DataFrame) -> DataFrame:
    """(group_id, items, weight): a database for each item, of its rows cut behind it."""
    rows = txw.select("items", "weight", F.posexplode("items").alias("p", "group_id"))
    return rows.select(F.col("group_id").cast("long").alias("group_id"), F.slice("items", F.lit(1), F.col("p") + 1).alias("items"), "weight").groupBy("group_id", "items").agg(F.sum("weight").alias("weight"))


def group_table(spark: SparkSession, groups: list[Group]) -> DataFrame:
    """(group_id, lo, hi, anchors, companions, allowed, est_nodes): n * groups numbers at most."""
    rows = []
    for g, x in enumerate(groups):
        companions = [*range(1, x.lo)] if x.companions is None else list(x.companions)
        rows.append((g, x.lo, x.hi, list(x.anchors), companions, sorted({*companions, *x.anchors}), float(x.est_nodes)))
    return spark.createDataFrame(rows, "group_id long, lo int, hi int, anchors array<int>, companions array<int>, allowed array<int>, est_nodes double")


def _group_of(groups: list[Group], n: int) -> Column:
    """An array that has each rank's group at its place (-1: none)."""
    of = [-1] * n
    for g, x in enumerate(groups):
        for a in x.anchors:
            of[a - 1] = g
    return F.lit(of) if of else F.array().cast("array<int>")


def by_group(txw: DataFrame, groups: list[Group], n: int) -> DataFrame:
    """(group_id, items, weight), equal rows of a group collapsed before they are sent to it."""
    spark = txw.sparkSession
    of = _group_of(groups, n)
    ids = F.array_distinct(F.filter(F.transform("items", lambda r: F.element_at(of, r)), lambda g: g >= 0))
    rows = txw.select("items", "weight", F.explode(ids).alias("g"))
    cuts = group_table(spark, groups).select("group_id", "hi", "anchors", "companions", "lo", "allowed")
    pruned = any(x.companions is not None or len(x.anchors) != x.hi - x.lo + 1 for x in groups)
    joined = rows.join(F.broadcast(cuts), F.col("g") == F.col("group_id"))  # n * groups numbers at most
    items = F.array_intersect("items", "allowed") if pruned else F.filter("items", lambda r: r <= F.col("hi"))
    out = joined.select("group_id", items.alias("items"), "weight", "anchors") if pruned else joined.select("group_id", items.alias("items"), "weight")
    return out.groupBy("group_id", "items").agg(F.sum("weight").alias("weight"))


def frequent_partners(pairs: DataFrame, min_count: int) -> DataFrame:
    return pairs.where(F.col("pair_count") >= min_count)


def prune_companions(groups: list[Group], frequent: dict[int, dict[int, int]]) -> list[Group]:
    """Companions that are frequent with no anchor of the group are left out. frequent: hi -> {lo: count} of frequent pairs."""
    out = []
    for g in groups:
        useful = set()
        for a in g.anchors:
            useful.update(k for k in frequent.get(a, ()) if k < g.lo)
        out.append(Group(g.lo, g.hi, g.est_nodes, sorted(useful), list(g.anchors)))
    return out


def short_circuit(groups: list[Group], frequent: dict[int, dict[int, int]], counts: dict[int, int]) -> tuple[list[tuple[tuple[int, ...], int]], list[Group]]:
    """Anchors with no or one frequent partner up to the group's last rank are answered from the counts and leave the group.

    A set is answered by its deeper item. If that one stays because it has other partners, it will be mined with the set; so an anchor that leaves
    answers its pair if it is the deeper of the two, or if the deeper one's mining would miss it, being in the same group without it.
    """
    direct: list[tuple[tuple[int, ...], int]] = []
    out = []
    for g in groups:
        own = set(g.anchors)
        partners: dict[int, set[int]] = {a: set(frequent.get(a, ())) for a in own}
        for a in own:
            for k in frequent.get(a, ()):
                if k in own:
                    partners[k].add(a)
        gone = {a for a in own if len(partners[a]) <= 1}
        pairs_out = set()
        for a in gone:
            direct.append(((a,), counts[a]))
            for b in partners[a]:
                pairs_out.add((max(a, b), min(a, b)))
        direct += [(p, frequent[p[0]][p[1]]) for p in sorted(pairs_out)]
        left = sorted(own - gone)
        if left:
            out.append(Group(g.lo, g.hi, g.est_nodes, g.companions, left))
    return direct, out


def partner_rows(pairs: DataFrame, groups: list[Group], n: int, min_count: int) -> DataFrame:
    """(group_id, anchor, items, weight): each frequent partner that an anchor has before it in its group, which so needs no scan to find it."""
    rows = frequent_partners(pairs, min_count).select(F.element_at(_group_of(groups, n), F.col("hi")).cast("long").alias("group_id"), F.col("hi").alias("anchor"), "lo", F.col("pair_count").alias("weight")).where("group_id >= 0")
    if any(x.companions is not None or len(x.anchors) != x.hi - x.lo + 1 for x in groups):  # what has left a group is no partner there
        rows = rows.join(group_table(pairs.sparkSession, groups).select("group_id", F.explode("allowed").alias("lo")), ["group_id", "lo"], "left_semi")
    return rows.select("group_id", "anchor", F.array("lo").alias("items"), "weight")


def planned_by_join(pairs: DataFrame, groups: list[Group], n: int, counts: dict[int, int], min_count: int) -> tuple[list[tuple[tuple[int, ...], int]], list[Group]]:
    """Short circuits and pruned companions as the two functions above find them, by joins; the driver gets a row for each anchor and a set for each group."""
    group_of = _group_of(groups, n)
    first = F.lit([g.lo for g in groups])
    f = frequent_partners(pairs, min_count).select("hi", "lo", "pair_count", F.element_at(group_of, F.col("hi")).alias("g"), F.element_at(group_of, F.col("lo")).alias("h"))
    both = f.where("g >= 0").select(F.col("hi").alias("a"), F.col("lo").alias("b"), "pair_count").unionByName(f.where("g >= 0 and g = h").select(F.col("lo").alias("a"), F.col("hi").alias("b"), "pair_count"))
    partners = {r["a"]: (r["n"], r["b"], r["c"]) for r in both.groupBy("a").agg(F.count(F.lit(1)).alias("n"), F.min("b").alias("b"), F.min("pair_count").alias("c")).collect()}  # n rows
    direct: list[tuple[tuple[int, ...], int]] = []
    left = []
    for g in groups:
        gone = [a for a in g.anchors if partners.get(a, (0,))[0] <= 1]
        direct += [((a,), counts[a]) for a in gone]
        one = {(max(a, partners[a][1]), min(a, partners[a][1])): partners[a][2] for a in gone if a in partners}
        direct += sorted(one.items())
        if stay := sorted(set(g.anchors) - set(gone)):
            left.append(Group(g.lo, g.hi, g.est_nodes, g.companions, stay))
    stays = F.lit([a for g in left for a in g.anchors]) if left else F.array().cast("array<int>")
    useful = f.where(F.array_contains(stays, F.col("hi")) & (F.col("lo") < F.element_at(first, F.col("g") + 1)))
    of = {r["g"]: sorted(r["useful"]) for r in useful.groupBy("g").agg(F.collect_set("lo").alias("useful")).collect()}  # n * groups numbers at most
    place = {g.lo: k for k, g in enumerate(groups)}
    return direct, [Group(g.lo, g.hi, g.est_nodes, of.get(place[g.lo], []), g.anchors) for g in left]
