"""The pilot: how many rows, in a given order, fill a prefix tree to its budget, and how large the tree then is.

A node appears with the first row that has its prefix. The rows' order is their tid, or a hash of it (which spreads the rows evenly, whatever their
place in the files). The stop is the largest order key at which the nodes that have appeared still fit; it is found from
histograms of first appearances, each BINS wide, narrowed until few enough are left to look at one by one.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import stage
from .localmine import Rows, Tree, _grow
from .prefixtree import exploded

BINS = 4096
#: First appearances looked at one by one.
FEW = 20_000
SPAN = 1 << 62
SEED = 17


@dataclass
class Pilot:
    rows: DataFrame  # the rows used: key k, items and, if the database has it, weight
    n_used: int
    n_total: int
    nodes: int
    aborted: bool
    stop: int | None = None  # the largest order key of the rows used; None: all

    @property
    def fraction(self) -> float:
        return self.n_used / self.n_total if self.n_total else 1.0

    @property
    def scale(self) -> float:
        return self.n_total / self.n_used if self.n_used else float("inf")


def order_key(order: str, seed: int = SEED) -> Column:
    return F.col("tid") if order == "tid" else F.pmod(F.xxhash64(F.lit(seed), "tid"), F.lit(SPAN))


def _stop(first: DataFrame, capacity: int) -> tuple[int | None, int]:
    """The largest key so that at most capacity nodes first appear at it or before (None if all do), and how many do."""
    lo, hi, total = first.agg(F.min("k"), F.max("k"), F.count(F.lit(1))).first()
    if total <= capacity:
        return None, total
    before = 0
    while True:
        inside = first.where((F.col("k") >= lo) & (F.col("k") <= hi))
        width = (hi - lo) // BINS + 1
        got = sorted((r["b"], r["count"]) for r in inside.groupBy(F.expr(f"(k - {lo}L) div {width}L").alias("b")).count().collect())  # BINS rows at most
        for b, n in got:
            if before + n > capacity:
                lo, hi = lo + b * width, min(hi, lo + (b + 1) * width - 1)
                break
            before += n
        if lo == hi:
            return lo - 1, before
        if n <= FEW:
            keys = np.sort(np.asarray([r["k"] for r in first.where((F.col("k") >= lo) & (F.col("k") <= hi)).select("k").collect()], np.int64))  # FEW rows at most
            stop = int(keys[capacity - before]) - 1
            return stop, before + int(np.searchsorted(keys, stop, side="right"))


def build_pilot(ranked: DataFrame, capacity: int, order: str = "hash", exact: bool = False) -> Pilot:
    """ranked: tid, items. With the hash order only a growing share of the rows is looked at, until the tree is over its capacity."""
    keyed = ranked.select(order_key(order).alias("k"), "items", *(["weight"] if "weight" in ranked.columns else []))
    n_total, cells = keyed.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.size("items")), F.lit(0))).first()
    share = min(1.0, 2 * capacity / max(cells, 1)) if order == "hash" else 1.0
    while True:
        some = keyed if share >= 1 else keyed.where(F.col("k") < int(share * SPAN))
        first = exploded(some, exact, "k").groupBy("node_key").agg(F.min("k").alias("k")).persist()
        stop, nodes = _stop(first, capacity)
        first.unpersist()
        if stop is not None or share >= 1:
            break
        share = min(1.0, share * 4)
    if stop is None:
        return Pilot(keyed, n_total, n_total, nodes, False)
    used = keyed.where(F.col("k") <= stop)
    return Pilot(used, used.count(), n_total, nodes, True, stop)


@dataclass
class QuickPilot:
    """What one task finds on the distinct rows in the order of their first places: the stop, nodes by item, and how many nodes of an item are above another's."""

    nodes: int
    n_used: int
    aborted: bool
    stop: int
    scale: float
    nu: np.ndarray
    above: DataFrame  # hi, lo, n: nodes of lo with a node of hi below them
    near: tuple[np.ndarray, np.ndarray, np.ndarray] | None  # the same on the driver, if the items are few
    tree: tuple[np.ndarray, np.ndarray] | None  # item and parent of each node, if asked for
    rows: DataFrame | None  # the rows that the tree holds, read back from it, if asked for

    def mu(self, pairs: DataFrame, frequent: dict[int, dict[int, int]] | None, min_count: int) -> np.ndarray:
        """Nodes of the tree of each item alone: those above its own that are of items frequent with it."""
        out = np.zeros(len(self.nu), np.int64)
        if frequent is None or self.near is None:
            wanted = pairs.where(F.col("pair_count") >= min_count).select("hi", "lo")
            for r in self.above.join(wanted, ["hi", "lo"]).groupBy("hi").agg(F.sum("n").alias("n")).collect():  # a row for each frequent item
                out[r["hi"]] = r["n"]
            return out
        for hi, lo, n in zip(*(x.tolist() for x in self.near), strict=True):
            if lo in frequent.get(hi, ()):
                out[hi] += n
        return out


#: Items up to which the driver adds up nodes by pairs; with more a join does.
PLANNED_ITEMS = 1000
PILOT = "kind string, hi int, lo int, n long, items array<int>"


def _pilot_task(n: int, capacity: int, want_tree: bool, want_rows: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, keys, cells, over, tested = [], [], 0, False, 0
        for b in batches:
            if over or not b.num_rows:
                continue
            lists = b.column(1)
            offsets = lists.offsets.to_numpy().astype(np.int64)
            parts.append(Rows(offsets - offsets[0], lists.flatten().to_numpy().astype(np.int64), b.column(2).to_numpy().astype(np.int64)))
            keys.append(b.column(0).to_numpy())
            cells += len(parts[-1].items)
            if cells - tested > capacity:  # a tree of fewer cells than the capacity fits; each test sees at least so many new ones
                parts, keys, tested = [Rows.joined(parts)], [np.concatenate(keys)], cells
                over = _grow(parts[0], n + 1, None, None)[1] > capacity
        rows, k = Rows.joined(parts) if parts else Rows.of([]), np.concatenate([np.zeros(0, np.int64), *keys])
        made = _grow(rows, n + 1, None, None)
        first = np.concatenate([np.zeros(0, np.int64), *(p[3] for p in made[0])])
        aborted, stop = len(first) > capacity, -1
        if aborted:  # nodes appear with their first rows, which are in the pilot's order
            k_first = np.sort(k[first])
            stop = int(k_first[capacity]) - 1
            m = int(np.searchsorted(k, stop, side="right"))
            rows = Rows(rows.offsets[: m + 1], rows.items[: rows.offsets[m]], rows.weights[:m])
        tree = Tree.of(rows, np.arange(n + 1), False)
        out: list[tuple] = [("aborted", 0, 0, int(aborted), None), ("stop", 0, 0, stop, None), ("nodes", 0, 0, tree.nodes(), None)]
        for j in range(1, n + 1):
            own = tree.of_item(j)
            if not len(own):
                continue
            out.append(("nu", j, 0, len(own), None))
            over_it, at = np.zeros(n + 1, np.int64), np.unique(tree.parent[own])
            seen = [np.zeros(0, np.int32)]
            while len(at := at[at >= 0]):
                seen.append(at)
                at = np.unique(tree.parent[at])
            every = np.unique(np.concatenate(seen))
            over_it = np.bincount(tree.item[every], minlength=n + 1)
            out += [("above", j, int(i), int(over_it[i]), None) for i in np.flatnonzero(over_it)]
            if len(out) > 20_000:
                yield _pilot_rows(out)
                out = []
        if want_tree:
            out += [("node", int(i), 0, int(p), None) for i, p in zip(tree.item, tree.parent, strict=True)]
        for lo in range(0, len(out), 20_000):
            yield _pilot_rows(out[lo : lo + 20_000])
        if want_rows:
            yield from _rows_of(tree)

    return run


def _rows_of(tree: Tree) -> Iterator[pa.RecordBatch]:
    """The rows that a tree was made of: the paths to nodes at which some of the count ends."""
    own = tree.count.copy()
    below = tree.parent >= 0
    np.subtract.at(own, tree.parent[below], tree.count[below])
    ends = np.flatnonzero(own > 0)
    for lo in range(0, len(ends), 20_000):
        some = ends[lo : lo + 20_000]
        path = tree.above(some, own[some], np.arange(len(tree.items)))
        size = np.diff(path.offsets) + 1
        offsets = np.append(0, np.cumsum(size))
        flat = np.empty(offsets[-1], np.int32)
        last = offsets[1:] - 1
        flat[last] = tree.item[some]
        before = np.ones(len(flat), bool)
        before[last] = False
        flat[before] = path.items
        n = len(some)
        yield pa.RecordBatch.from_arrays([pa.array(["row"] * n, pa.string()), pa.array(np.zeros(n, np.int32)), pa.array(np.zeros(n, np.int32)), pa.array(own[some]), pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(flat))], names=["kind", "hi", "lo", "n", "items"])


def _pilot_rows(rows: list[tuple]) -> pa.RecordBatch:
    kind, hi, lo, n, items = zip(*rows, strict=True)
    return pa.RecordBatch.from_arrays([pa.array(kind, pa.string()), pa.array(hi, pa.int32()), pa.array(lo, pa.int32()), pa.array(n, pa.int64()), pa.array(items, pa.list_(pa.int32()))], names=["kind", "hi", "lo", "n", "items"])


def quick_pilot(txw: DataFrame, n: int, capacity: int, cells: int, n_total: int, hashed: bool, want_tree: bool = False, want_rows: bool = False, count_upto: Callable[[int], int] | None = None, keep: Callable[[DataFrame], DataFrame] = stage) -> QuickPilot:
    """The pilot over distinct rows (items, weight, k), where k is a row's first place, by one task that stops at the capacity.

    As a row's nodes appear where it first occurs, distinct rows give the stop that all rows would. With the hash order only a share of the rows is sent to the task, which grows
    until it fills the tree; the number of baskets before the stop is then the stop's share of the hash range. In the order of tid all rows are sent.
    """
    share = min(1.0, 2 * capacity / max(cells, 1)) if hashed else 1.0
    while True:
        some = txw if share >= 1 else txw.where(F.col("k") < int(share * SPAN))
        found = keep(some.select("k", "items", "weight").repartition(1).sortWithinPartitions("k").mapInArrow(_pilot_task(n, capacity, want_tree, want_rows), PILOT))
        few = n <= PLANNED_ITEMS
        facts = found.where("kind in ('aborted', 'stop', 'nodes', 'nu', 'node')" + " or kind = 'above'" * few).select("kind", "hi", "lo", "n").toArrow()  # a row for each item, for each pair of few ones, and for each node of the tree if asked for
        kind, hi, value = facts["kind"].to_pylist(), facts["hi"].to_numpy(), facts["n"].to_numpy()
        one = {k: int(v) for k, v in zip(kind, value, strict=True) if k in ("aborted", "stop", "nodes")}
        if one["aborted"] or share >= 1:
            break
        share = min(1.0, share * 8)
    nu = np.zeros(n + 1, np.int64)
    is_nu = np.asarray([k == "nu" for k in kind], bool)
    nu[hi[is_nu]] = value[is_nu]
    near = None
    if few:
        is_above = np.asarray([k == "above" for k in kind], bool)
        near = (hi[is_above], facts["lo"].to_numpy()[is_above], value[is_above])
    tree = None
    if want_tree:
        is_node = np.asarray([k == "node" for k in kind], bool)
        tree = (hi[is_node].astype(np.int64), value[is_node].astype(np.int64))
    if not one["aborted"]:
        used, scale = n_total, 1.0
    elif hashed:
        used = max(1, round(n_total * (one["stop"] + 1) / SPAN))
        scale = SPAN / max(1, one["stop"] + 1)
    else:
        used = max(1, count_upto(one["stop"]))
        scale = n_total / used
    rows = found.where("kind = 'row'").select("items", F.col("n").alias("weight")) if want_rows and one["aborted"] else None
    return QuickPilot(one["nodes"], used, bool(one["aborted"]), one["stop"], scale, nu, found.where("kind = 'above'").select("hi", "lo", "n"), near, tree, rows)
