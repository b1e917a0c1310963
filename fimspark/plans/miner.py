"""Miners by divide and conquer over projected databases.

A database is one table of distinct ranked rows with weights, written once; all else is read from it. A level is one job: all groups' rows go from it straight to the tasks that
mine them, a task for each group, and answers and the groups that turned out too large come back as rows of one table in the shared folder. A prefix head
of more than half of the items is not written at all: one task fills its tree from the table itself. The driver sees plans and counts only. Each frequent set
is answered by the group of its least frequent item, so answers are put together without comparing them.

No task makes a tree over the budget. A group whose tree would be larger is reported instead: one of several anchors is halved, a lone anchor becomes a database of its own, which
has fewer items, so this ends.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import encode, paircounts, project
from ..operators.localmine import Counters, Rows, mine_group
from ..operators.pilot import SPAN, order_key, quick_pilot
from ..operators.prefixtree import exploded
from ..operators.stats import StatsBundle
from ..session import release, stage
from .budget import BudgetExceeded, nodes_for_bytes, usable_nodes
from .grouping import Group, equal_groups, plan
from .ledger import CostLedger

FI = "itemset array<int>, support_count long"
LEVEL = "group_id long, status string, itemset array<int>, support_count long"
#: Frequent pairs that the planner reads on the driver; with more it plans by joins.
MAX_PLANNED_PAIRS = 200_000
#: Large single-anchor databases that are planned at the same time.
SIDE_BY_SIDE = 8
#: A head is read by one task if the table has at most this many items; a larger table is cut and collapsed by all tasks first.
HEAD_CELLS = 50_000_000
#: Partitions of a level's groups: two for each group up to this.
MAX_TASKS = 2000
#: Answers that a task sends at once.
BATCH = 20_000


@dataclass
class MiningResult:
    """fi: (itemset STRING, size, support_count); groups: one row for each group mined, and with sizes for each that was planned for the table itself and no task could hold. Their depth is 0 if planned for, or split from, the table itself."""

    fi: DataFrame
    order: DataFrame
    min_count: int
    groups: list[dict] = field(default_factory=list)
    ledger: CostLedger = field(default_factory=CostLedger)
    stats: list[StatsBundle] = field(default_factory=list)
    counters: Counters = field(default_factory=Counters)
    scratch: list[DataFrame] = field(default_factory=list)  # stages that the answer does not read

    def keep(self, df: DataFrame) -> DataFrame:
        """A stage that is removed when the run is done."""
        out = stage(df)
        self.scratch.append(out)
        return out


@dataclass
class Prepared:
    ranked: DataFrame
    order: DataFrame
    counts: dict[int, int]
    min_count: int
    n: int
    names: list[str] | None = None
    n_tx: int = 0


def prepare(tx: DataFrame, min_support: float | int, strict: bool = False, staged: bool = True) -> Prepared:
    """Both scans that every miner starts with: count the items, then rank the baskets. staged: the ranked rows are written."""
    spark = tx.sparkSession
    counted = stage(encode.count_items_and_rows(tx))
    n_tx = counted.where("item IS NULL").agg(F.sum("item_count")).first()[0] or 0
    mc = encode.resolve_min_count(n_tx, min_support, strict)
    items = counted.where("item IS NOT NULL")
    t = items.where(F.col("item_count") >= mc).limit(encode.MAX_SENT_ITEMS + 1).toArrow()
    if t.num_rows <= encode.MAX_SENT_ITEMS:
        by = sorted(zip(t["item"].to_pylist(), t["item_count"].to_pylist(), strict=True), key=lambda x: (-x[1], x[0].encode()))
        names = [x for x, _ in by]
        counts = {k + 1: c for k, (_, c) in enumerate(by)}
        order = spark.createDataFrame([(x, k + 1, c) for k, (x, c) in enumerate(by)], "item string, item_rank int, item_count long")
    else:
        names, order = None, stage(encode.frequency_order(items, mc))
        counts = {r["item_rank"]: r["item_count"] for r in order.select("item_rank", "item_count").collect()}  # two numbers for each frequent item
    ranked = encode.rank_transactions(tx, order, names).where(F.size("items") > 0)
    return Prepared(stage(ranked) if staged else ranked, order, counts, mc, len(counts), names, n_tx)


def _lists(b: pa.RecordBatch, ok: np.ndarray) -> Rows:
    lists = b.column(2).filter(pa.array(ok)) if not ok.all() else b.column(2)
    offsets = lists.offsets.to_numpy().astype(np.int64)
    return Rows(offsets - offsets[0], lists.flatten().to_numpy().astype(np.int64), b.column(3).to_numpy()[ok].astype(np.int64))


def _level_rows(g: int, rows: list[tuple[str, tuple[int, ...] | None, int]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays(
        [pa.array([g] * len(rows), pa.int64()), pa.array([s for s, _, _ in rows], pa.string()), pa.array([x for _, x, _ in rows], pa.list_(pa.int32())), pa.array([c for _, _, c in rows], pa.int64())],
        names=["group_id", "status", "itemset", "support_count"],
    )


def _mine_task(anchors: dict[int, list[int]], path_of: Callable[[int], tuple[int, ...]], min_count: int, capacity: int | None, max_len: int | None, use_array: bool, shared_tree: bool, collapsed: bool = True):
    """A group's rows to answer rows, or, if its tree would pass the capacity, to one row that says so.

    Rows (group_id, anchor, items, weight) are baskets, or, if anchor is not 0, a frequent partner of that anchor with the count of both. collapsed: no two baskets are equal; each
    then has a node of its own, so more baskets than nodes need not be kept.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, pairs, g, n, cells, over = [], [], None, 0, 0, False
        for b in batches:
            if not b.num_rows:
                continue
            g = b.column(0)[0].as_py()
            if over:
                continue
            anchor = b.column(1).to_numpy()
            if (anchor > 0).any():
                some = _lists(b, anchor > 0)
                pairs.append(np.stack([anchor[anchor > 0], some.items, some.weights]))
            if (anchor == 0).any():
                parts.append(_lists(b, anchor == 0))
                n += len(parts[-1])
                cells += len(parts[-1].items)
                many = capacity is not None and n > capacity
                if not collapsed and (many or cells > 1_000_000):
                    parts = [Rows.joined(parts).collapsed()]
                    n, cells = len(parts[0]), len(parts[0].items) // 2
                    many = capacity is not None and n > capacity
                if many:  # more distinct baskets than nodes
                    over, parts = True, []
        if g is None:
            return
        stats = Counters()
        if over:
            yield _level_rows(g, [("needs_split", None, n)])
            return
        if parts and not collapsed:
            parts = [Rows.joined(parts).collapsed()]
        rows = Rows.joined(parts) if parts else Rows.of([])
        known = None
        if pairs:
            a, lo, c = np.concatenate(pairs, axis=1)
            by = np.lexsort((lo, a))
            a, lo, c = a[by], lo[by], c[by]
            kinds, first = np.unique(a, return_index=True)
            known = {int(k): (x, y) for k, x, y in zip(kinds, np.split(lo, first[1:]), np.split(c, first[1:]), strict=True)}
        own = anchors[g] if anchors else [int(rows.items.max())] if len(rows.items) else []
        held: list = []
        try:
            for s, c in mine_group(rows, own, min_count, path_of(g), max_len=max_len, use_array=use_array, shared_tree=shared_tree, stats=stats, partners=known, capacity=capacity):
                held.append(("fi", s, c))
                if len(held) >= BATCH:
                    yield _level_rows(g, held)
                    held = []
        except BudgetExceeded:
            yield _level_rows(g, [("needs_split", None, n)])
            return
        yield _level_rows(g, [*held, ("nodes", None, stats.nodes), ("held", None, stats.held), ("traversals", None, stats.traversals), ("trees", None, stats.trees)])

    return run


def mine_level(
    proj: DataFrame,
    anchors: dict[int, list[int]],
    min_count: int,
    *,
    paths: dict[int, tuple[int, ...]] | Callable[[int], tuple[int, ...]] | None = None,
    capacity: int | None = None,
    max_len: int | None = None,
    use_array: bool = True,
    shared_tree: bool = True,
    partners: DataFrame | None = None,
    direct: bool = False,
) -> DataFrame:
    """(group_id, status, itemset, support_count), written to the shared folder. anchors empty: a group's anchor is its last rank.

    A group over capacity is not mined but reported as needs_split. partners: (group_id, anchor, items, weight), frequent partners that go with the groups' rows. direct: proj is one
    group, whose rows are read by one task without being sent anywhere. Where anchors are given, each group gets a partition
    of its own, small as its rows may be.
    """
    path_of = paths if callable(paths) else (paths or {}).get
    named = path_of if callable(paths) else lambda g: path_of(g, ())
    rows = proj.select("group_id", F.lit(0).alias("anchor"), "items", "weight")
    rows = rows if partners is None else rows.unionByName(partners.select("group_id", "anchor", "items", "weight"))
    task = _mine_task(anchors, named, min_count, capacity, max_len, use_array, shared_tree, not direct)
    if direct:
        return stage(rows.coalesce(1).mapInArrow(task, LEVEL))
    if anchors:
        rows = rows.repartition(min(2 * len(anchors), MAX_TASKS), "group_id")
    return stage(rows.groupBy("group_id").applyInArrow(task, LEVEL))


def _notes(level: DataFrame, result: MiningResult) -> dict[int, int]:
    nodes = {}
    for r in level.where("status in ('nodes', 'held', 'traversals', 'trees')").select("group_id", "status", "support_count").collect():  # four rows a group
        if r["status"] == "nodes":
            nodes[r["group_id"]] = r["support_count"]
            result.counters.nodes = max(result.counters.nodes, r["support_count"])
        elif r["status"] == "held":
            result.counters.held = max(result.counters.held, r["support_count"])
        else:
            setattr(result.counters, r["status"], getattr(result.counters, r["status"]) + r["support_count"])
    return nodes


def _answers(level: DataFrame) -> DataFrame:
    return level.where("status = 'fi'").select("itemset", "support_count")


def _finish(parts: list[DataFrame], direct: list[tuple[tuple[int, ...], int]], prep: Prepared, result: MiningResult, max_len: int | None) -> MiningResult:
    spark = prep.order.sparkSession
    direct = [(list(s), c) for s, c in direct if max_len is None or len(s) <= max_len]
    fi = spark.createDataFrame(direct, FI) if direct or not parts else None  # two sets for each item at most
    for p in parts:
        fi = p if fi is None else fi.unionByName(p)
    result.fi = encode.decode(fi, prep.order, prep.names)
    release(*result.scratch)
    result.scratch.clear()
    return result


def _large(level: DataFrame) -> list[int]:
    return sorted(r["group_id"] for r in level.where("status = 'needs_split'").select("group_id").collect())  # a row for each group at most


def _tree_sizes(proj: DataFrame, anchors: dict[int, list[int]], pairs: DataFrame, min_count: int, shared_tree: bool) -> dict[int, int]:
    """Nodes of the whole trees that these groups have, by counting distinct prefixes of their rows, as no task can make them.

    As in a task, a group of several anchors has one tree of its rows; else an anchor has a tree of its frequent partners, if there are two or more.
    """
    apart = {g: a for g, a in anchors.items() if len(a) == 1 or not shared_tree}
    trees = proj.where(F.col("group_id").isin([g for g in anchors if g not in apart])).select("group_id", F.lit(0).alias("anchor"), "items")
    if apart:
        own = proj.sparkSession.createDataFrame([(g, a) for g, some in apart.items() for a in some], "group_id long, anchor int")
        wanted = own.join(project.frequent_partners(pairs, min_count), F.col("hi") == F.col("anchor")).groupBy("group_id", "anchor").agg(F.collect_set("lo").alias("wanted"))  # n numbers for each anchor at most
        rows = proj.join(wanted, "group_id").where(F.array_contains("items", F.col("anchor")))
        trees = trees.unionByName(rows.select("group_id", "anchor", F.array_intersect("items", "wanted").alias("items")))
    nodes = exploded(trees, True, "group_id", "anchor").select("group_id", "anchor", "node_key", "item_rank").distinct()
    each = nodes.groupBy("group_id", "anchor").agg(F.count(F.lit(1)).alias("n"), (F.min("item_rank") < F.max("item_rank")).alias("several"))
    found = each.where("anchor = 0 or several").groupBy("group_id").agg(F.sum("n").alias("n")).collect()  # a row for each group
    return dict.fromkeys(anchors, 0) | {r["group_id"]: r["n"] for r in found}


def _settle(proj: DataFrame, level: DataFrame, anchors: dict[int, list[int]], counts: dict[int, int], min_count: int, capacity: int, result: MiningResult, options: dict, how: dict, path: tuple[int, ...]) -> list[DataFrame]:
    """Groups that were too large: several anchors are halved and projected from the group's own rows, a lone one becomes a database of its own, until all fit."""
    parts: list[DataFrame] = []
    next_id = max(anchors, default=0) + 1
    while large := _large(level):
        kept = result.keep(proj.where(F.col("group_id").isin(large)))
        result.ledger.measure("projected again", kept)
        lone = [g for g in large if len(anchors[g]) == 1]
        # these databases do not depend on each other: their planning jobs run side by side
        with ThreadPoolExecutor(SIDE_BY_SIDE) as pool:
            for more in pool.map(lambda g: _recurse(kept.where(F.col("group_id") == g), anchors[g][0], counts, min_count, capacity, result, options, how, path), lone):
                parts += more
        halves: dict[int, list[int]] = {}
        cuts = []
        for g in large:
            own = sorted(anchors[g])
            for half in (own[: len(own) // 2], own[len(own) // 2 :]) if len(own) > 1 else ():
                halves[next_id] = half
                cuts.append((g, next_id, half, half[-1]))
                next_id += 1
        if not halves:
            break
        table = proj.sparkSession.createDataFrame(cuts, "group_id long, half long, anchors array<int>, hi int")
        rows = kept.join(F.broadcast(table), "group_id").where(F.arrays_overlap("items", "anchors"))  # the anchors of large groups
        proj = rows.select(F.col("half").alias("group_id"), F.filter("items", lambda r: r <= F.col("hi")).alias("items"), "weight").groupBy("group_id", "items").agg(F.sum("weight").alias("weight"))
        level = mine_level(result.ledger.watch("projected again", proj), halves, min_count, capacity=capacity, paths={g: path for g in halves}, **options)
        result.ledger.settle()
        nodes = _notes(level, result)
        result.groups += [{"group_id": g, "lo": min(a), "hi": max(a), "est_nodes": None, "real_nodes": nodes[g], "how": "split", "depth": how.get("depth", 0)} for g, a in halves.items() if g in nodes]
        parts.append(_answers(level))
        anchors = halves
    return parts


def mine_budgeted(
    tx: DataFrame,
    min_support: float | int,
    node_budget: int | None = None,
    *,
    memory: int | None = None,
    cut: str = "nu_mu",
    packing: str = "mu_sum",
    prune: bool = True,
    reuse_pilot: bool = True,
    bypass_head: bool = True,
    array: bool = True,
    shared_tree: bool = True,
    order: str = "hash",
    strict: bool = False,
    max_len: int | None = None,
    measure: bool = False,
    sizes: bool = False,
) -> MiningResult:
    """Pilot tree first; if the database's tree does not fit, statistics, groups that do, one projection, and a task for each group.

    The budget is one of nodes, or of bytes (memory) that hold as many nodes. reuse_pilot: the rows that filled the pilot's tree are projected from that tree, and only the others are read again.
    sizes: groups planned for the table itself whose trees turn out too large for a task are in the result's groups too, with the sizes of these trees, which a job of its own counts.
    """
    node_budget = nodes_for_bytes(memory) if node_budget is None and memory is not None else node_budget
    if node_budget is None:
        raise ValueError("a budget is needed: node_budget or memory")
    prep = prepare(tx, min_support, strict, staged=False)
    result = MiningResult(prep.ranked, prep.order, prep.min_count)
    result.ledger.on = measure
    options = {"max_len": max_len, "use_array": array, "shared_tree": shared_tree}
    txw = result.keep(prep.ranked.select("items", order_key(order).alias("k")).groupBy("items").agg(F.count(F.lit(1)).alias("weight"), F.min("k").alias("k"))) if prep.n else None
    how = dict(cut=cut, packing=packing, prune=prune, reuse_pilot=reuse_pilot, bypass_head=bypass_head, order=order, sizes=sizes, count_upto=lambda stop: prep.ranked.where(order_key(order) <= stop).count())
    parts, direct = _mine_database(txw, prep.n, prep.counts, prep.min_count, usable_nodes(node_budget), result, options, how, ())
    return _finish(parts, direct, prep, result, max_len)


def _frequent(pairs: DataFrame, min_count: int) -> dict[int, dict[int, int]] | None:
    """hi -> {lo: count} of frequent pairs, or None if they are too many for the driver."""
    out: dict[int, dict[int, int]] = {}
    t = project.frequent_partners(pairs, min_count).limit(MAX_PLANNED_PAIRS + 1).toArrow()
    if t.num_rows > MAX_PLANNED_PAIRS:
        return None
    for hi, lo, c in zip(t["hi"].to_pylist(), t["lo"].to_pylist(), t["pair_count"].to_pylist(), strict=True):
        out.setdefault(hi, {})[lo] = c
    return out


def _mine_database(txw: DataFrame | None, n: int, counts: dict[int, int], min_count: int, capacity: int, result: MiningResult, options: dict, how: dict, path: tuple[int, ...]) -> tuple[list[DataFrame], list]:
    """txw: (items, weight, k), written; ranks 1..n are frequent, and all sets are joined to the path. k: a row's first place in the pilot's order."""
    if not n:
        return [], []
    ledger = result.ledger
    size = F.size("items")
    rows, cells, n_total, all_cells = txw.agg(F.count(F.lit(1)), F.coalesce(F.sum(size), F.lit(0)), F.coalesce(F.sum("weight"), F.lit(0)), F.coalesce(F.sum(size * F.col("weight")), F.lit(0))).first()
    ledger.add("ranked", n_total, all_cells)
    ledger.add("collapsed", rows, cells)
    pilot = None
    if cells > capacity:  # else the tree fits whatever the rows are
        with ThreadPoolExecutor(2) as pool:  # pair counts are cheap where they turn out not to be needed: there are few distinct rows then
            counting = pool.submit(lambda: result.keep(paircounts.pair_matrix(txw, n)))
            pilot = quick_pilot(txw, n, capacity, cells, n_total, how["order"] == "hash", how["packing"] == "union", how["reuse_pilot"], how.get("count_upto"), result.keep)
            pairs = counting.result()
    if pilot is None or not pilot.aborted:
        level = mine_level(txw.select(F.lit(0).cast("long").alias("group_id"), "items", "weight"), {0: [*range(1, n + 1)]}, min_count, paths={0: path}, capacity=capacity, **options)
        nodes = _notes(level, result)
        result.groups.append({"group_id": 0, "lo": 1, "hi": n, "est_nodes": float(nodes.get(0, 0)), "real_nodes": nodes.get(0), "how": "whole", "depth": how.get("depth", 0)})
        return [_answers(level)], []
    ledger.measure("pairs", pairs.select(F.array("hi", "lo").alias("items")))
    if pilot.rows is not None:
        ledger.measure("pilot rows", pilot.rows)
    frequent = _frequent(pairs, min_count)
    stats = StatsBundle(n, n_total, pilot.n_used, pilot.nodes, np.cumsum(pilot.nu), pilot.mu(pairs, frequent, min_count), pilot.scale)
    result.stats.append(stats)
    groups = plan(stats, max(1, pilot.nodes), how["cut"], how["packing"], pilot.tree)
    direct: list[tuple[tuple[int, ...], int]] = []
    if how["prune"]:
        if frequent is None:
            direct, groups = project.planned_by_join(pairs, groups, n, counts, min_count)
        else:
            direct, groups = project.short_circuit(groups, frequent, counts)
            groups = project.prune_companions(groups, frequent)
        direct = [((*path, *s), c) for s, c in direct]
    # a head of more than half of the items is mined from the table itself
    head = [g for g in groups if how["bypass_head"] and g.lo == 1 and 2 * len(g.anchors) > n]
    rest = [g for g in groups if g not in head]
    numbered = dict(enumerate([*head, *rest]))
    if not numbered:
        return [], direct
    anchors = {k: g.anchors for k, g in numbered.items()}
    partners = project.partner_rows(pairs, [*head, *rest], n, min_count) if options["use_array"] else None
    shared = dict(paths={k: path for k in numbered}, capacity=capacity, **options)
    source = txw if pilot.rows is None else pilot.rows.unionByName(txw.where(F.col("k") > pilot.stop).select("items", "weight"))
    proj = project.by_group(source, rest, n).withColumn("group_id", F.col("group_id") + len(head)) if rest else None
    cut = collapsed = None
    if head:
        g = head[0]
        # pruned or not, the head's rows are what its anchors leave of a row
        cut = txw.where(F.element_at("items", 1) <= g.hi).select(F.lit(0).cast("long").alias("group_id"), F.array_intersect("items", F.lit(sorted({*g.anchors, *(g.companions or [])}))).alias("items"), "weight").where(F.size("items") > 0)
        collapsed = cut.groupBy("group_id", "items").agg(F.sum("weight").alias("weight"))

    def of_head() -> DataFrame | None:
        if cut is None:
            return None
        own = None if partners is None else partners.where("group_id = 0")
        if cells <= HEAD_CELLS:
            ledger.add("head", 0, 0)
            return mine_level(cut, anchors, min_count, partners=own, direct=True, **shared)
        return mine_level(ledger.watch("head", collapsed), anchors, min_count, partners=own, **shared)

    def of_rest() -> DataFrame | None:
        if proj is None:
            return None
        own = None if partners is None else partners.where(F.col("group_id") >= len(head))
        return mine_level(ledger.watch("projected", proj), anchors, min_count, partners=own, **shared)

    with ThreadPoolExecutor(2) as pool:
        levels = [x for x in (f.result() for f in (pool.submit(of_head), pool.submit(of_rest))) if x is not None]
    ledger.settle()
    level = levels[0] if len(levels) == 1 else levels[0].unionByName(levels[1])
    nodes = _notes(level, result)
    every = [x for x in (collapsed, proj) if x is not None]
    every = every[0] if len(every) == 1 else every[0].unionByName(every[1])
    real = nodes
    if how.get("sizes") and len(nodes) < len(numbered):
        real = nodes | _tree_sizes(every, {k: a for k, a in anchors.items() if k not in nodes}, pairs, min_count, options["shared_tree"])
    result.groups += [{"group_id": k, "lo": g.lo, "hi": g.hi, "est_nodes": g.est_nodes, "real_nodes": real[k], "how": "head" if k < len(head) else "group", "depth": how.get("depth", 0)} for k, g in numbered.items() if k in real]
    parts = [_answers(level)]
    if len(nodes) < len(numbered):
        parts += _settle(every, level, anchors, counts, min_count, capacity, result, options, how, path)
    return parts, direct


def _recurse(rows: DataFrame, a: int, counts: dict[int, int], min_count: int, capacity: int, result: MiningResult, options: dict, how: dict, path: tuple[int, ...]) -> list[DataFrame]:
    """A lone anchor too large for a task: its database, without the anchor and in an order of its own, is mined as a database of its own."""
    spark = rows.sparkSession
    out = [spark.createDataFrame([([*path, a], counts[a])], FI)]
    left = None if options["max_len"] is None else options["max_len"] - 1
    below = rows.select(F.array_remove("items", a).alias("items"), "weight").where(F.size("items") > 0)
    t = below.select("weight", F.explode("items").alias("item")).groupBy("item").agg(F.sum("weight").alias("c")).where(F.col("c") >= min_count).toArrow()  # the anchor's frequent partners
    local = sorted(zip(t["item"].to_pylist(), t["c"].to_pylist(), strict=True), key=lambda x: (-x[1], x[0]))
    if not local or left == 0:
        return out
    place = [0] * a
    for r, (item, _) in enumerate(local, 1):
        place[item - 1] = r
    ranks = F.array_sort(F.filter(F.transform("items", lambda r: F.element_at(F.lit(place), r)), lambda r: r > 0))
    again = below.select(ranks.alias("items"), "weight").where(F.size("items") > 0).groupBy("items").agg(F.sum("weight").alias("weight"))
    txw = result.keep(again.withColumn("k", F.pmod(F.xxhash64("items"), F.lit(SPAN))))
    parts, direct = _mine_database(txw, len(local), {r: c for r, (_, c) in enumerate(local, 1)}, min_count, capacity, result, {**options, "max_len": left}, {**how, "order": "hash", "depth": how.get("depth", 0) + 1, "sizes": False}, ())
    # back to the ranks of the database that the anchor came from
    back = F.lit([item for item, _ in local])
    got = spark.createDataFrame([(list(s), c) for s, c in direct if left is None or len(s) <= left], FI)
    for p in parts:
        got = got.unionByName(p)
    return [*out, got.select(F.concat(F.lit([*path, a]), F.transform("itemset", lambda r: F.element_at(back, r))).alias("itemset"), "support_count")]


def mine_per_item(tx: DataFrame, min_support: float | int, node_budget: int | None = None, *, use_array: bool = False, strict: bool = False, max_len: int | None = None, measure: bool = False) -> MiningResult:
    """A projected database for each item, mined by plain growth. One over the budget is projected again, by its own items, until each part fits."""
    prep = prepare(tx, min_support, strict, staged=False)
    result = MiningResult(prep.ranked, prep.order, prep.min_count)
    ledger, mc = result.ledger, prep.min_count
    ledger.on = measure
    capacity = usable_nodes(node_budget) if node_budget else None
    txw = encode.collapse(prep.ranked)
    if measure:
        ledger.measure("ranked", prep.ranked)
    proj, depth, step = project.per_item(txw), 0, prep.n + 1
    bases: list[tuple[int, ...]] = [()]
    parts: list[DataFrame] = []
    while True:
        path_of = (lambda bases: lambda g: bases[g // step])(bases)
        level = mine_level(ledger.watch("projected", proj), {}, mc, max_len=max_len, use_array=use_array, capacity=capacity, paths=path_of)
        ledger.settle()
        nodes = _notes(level, result)
        result.groups += [{"group_id": k, "lo": k % step, "hi": k % step, "est_nodes": None, "real_nodes": v, "how": "item", "depth": depth} for k, v in sorted(nodes.items())]
        parts.append(_answers(level))
        large = _large(level) if capacity is not None else []
        if not large:
            return _finish(parts, [], prep, result, max_len)
        kept = result.keep(proj.where(F.col("group_id").isin(large)))
        ledger.measure("projected again", kept)
        paths = [(*path_of(g), g % step) for g in large]
        own = kept.groupBy("group_id").agg(F.sum("weight").alias("support_count"))
        spark = tx.sparkSession
        table = F.broadcast(spark.createDataFrame([(g, k, list(p)) for k, (g, p) in enumerate(zip(large, paths, strict=True))], "group_id long, base long, path array<int>"))  # a row for each large database
        parts.append(stage(own.join(table, "group_id").select(F.col("path").alias("itemset"), "support_count")))
        # without the anchor and what is not frequent with it
        below = kept.join(table, "group_id").select("base", F.slice("items", F.lit(1), F.size("items") - 1).alias("items"), "weight")
        allowed = below.select("base", F.explode("items").alias("item"), "weight").groupBy("base", "item").agg(F.sum("weight").alias("c")).where(F.col("c") >= mc).groupBy("base").agg(F.collect_set("item").alias("allowed"))  # a set for each large database
        narrow = below.join(allowed, "base").select("base", F.array_intersect("items", "allowed").alias("items"), "weight").where(F.size("items") > 0).groupBy("base", "items").agg(F.sum("weight").alias("weight"))
        each = narrow.select("base", "items", "weight", F.posexplode("items").alias("p", "item"))
        proj = each.select((F.col("base") * step + F.col("item")).alias("group_id"), F.slice("items", F.lit(1), F.col("p") + 1).alias("items"), "weight").groupBy("group_id", "items").agg(F.sum("weight").alias("weight"))
        bases, depth = paths, depth + 1


def mine_equal_groups(tx: DataFrame, min_support: float | int, k: int, node_budget: int | None = None, *, use_array: bool = True, strict: bool = False, max_len: int | None = None, measure: bool = False) -> MiningResult:
    """k groups of equally many items, as the cost analysis has it."""
    prep = prepare(tx, min_support, strict, staged=False)
    result = MiningResult(prep.ranked, prep.order, prep.min_count)
    result.ledger.on = measure
    groups = equal_groups(prep.n, k)
    if not groups:
        return _finish([], [], prep, result, max_len)
    proj = project.by_group(encode.collapse(prep.ranked), groups, prep.n)
    if measure:
        result.ledger.measure("ranked", prep.ranked)
    anchors = dict(enumerate(g.anchors for g in groups))
    capacity = usable_nodes(node_budget) if node_budget else None
    options = {"max_len": max_len, "use_array": use_array, "shared_tree": True}
    level = mine_level(result.ledger.watch("projected", proj), anchors, prep.min_count, capacity=capacity, **options)
    result.ledger.settle()
    nodes = _notes(level, result)
    result.groups = [{"group_id": g, "lo": x.lo, "hi": x.hi, "est_nodes": None, "real_nodes": nodes.get(g), "how": "equal"} for g, x in enumerate(groups)]
    parts = [_answers(level)]
    if capacity is not None and len(nodes) < len(groups):
        how = dict(cut="nu_mu", packing="mu_sum", prune=True, reuse_pilot=False, bypass_head=True, order="hash")
        parts += _settle(proj, level, anchors, prep.counts, prep.min_count, capacity, result, options, how, ())
    return _finish(parts, [], prep, result, max_len)


def divide_and_conquer(txw: DataFrame, fits: Callable[[DataFrame], bool], decompose: Callable[[DataFrame], list[DataFrame]], mine: Callable[[DataFrame], DataFrame], combine: Callable[[list[DataFrame]], DataFrame], levels: int = 6) -> DataFrame:
    """The general scheme, with its four parts as parameters."""
    if levels <= 0 or fits(txw):
        return mine(txw)
    return combine([divide_and_conquer(x, fits, decompose, mine, combine, levels - 1) for x in decompose(txw)])


__all__ = ["FI", "Group", "MiningResult", "Prepared", "divide_and_conquer", "mine_budgeted", "mine_equal_groups", "mine_level", "mine_per_item", "prepare"]
