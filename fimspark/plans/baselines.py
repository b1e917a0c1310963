"""The methods that the budgeted miner is compared with. All but sampling give the same answers."""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import encode
from ..operators.localmine import Rows, mine_all
from ..operators.prefixtree import exploded
from ..session import shared_dir, stage
from .decompose import by_partition
from .ledger import CostLedger
from .miner import FI, MiningResult, _answers, _finish, _notes, mine_level, mine_per_item, prepare

#: Candidates that are sent to all tasks for counting; more are counted by a join.
MAX_SENT_CANDIDATES = 500_000


def per_item_projection(tx: DataFrame, min_support: float | int, node_budget: int | None = None, **kw) -> MiningResult:
    return mine_per_item(tx, min_support, node_budget, use_array=False, **kw)


def in_memory(tx: DataFrame, min_support: float | int, use_array: bool = True, max_len: int | None = None) -> MiningResult:
    """No decomposition: the whole tree in one task."""
    prep = prepare(tx, min_support)
    result = MiningResult(prep.ranked, prep.order, prep.min_count)
    whole = encode.collapse(prep.ranked).select(F.lit(0).cast("long").alias("group_id"), "items", "weight")
    level = mine_level(whole, {0: [*range(1, prep.n + 1)]}, prep.min_count, max_len=max_len, use_array=use_array)
    _notes(level, result)
    return _finish([_answers(level)], [], prep, result, max_len)


def count_candidates(ranked: DataFrame, candidates: DataFrame, n: int, by: str = "auto") -> DataFrame:
    """(itemset, support_count) of candidate sets of ranks over all rows.

    by: send (candidates to all tasks, which send back partial counts), shuffle (rows and candidates meet by the candidate's first item), or auto: by their number.
    """
    if by == "auto":
        by = "send" if candidates.limit(MAX_SENT_CANDIDATES + 1).count() <= MAX_SENT_CANDIDATES else "shuffle"
    w = F.col("weight") if "weight" in ranked.columns else F.lit(1).cast("long")
    rows = ranked.select("items", w.alias("weight"))
    if by == "shuffle":
        first = candidates.select("itemset", F.element_at("itemset", 1).alias("item"))
        long = rows.select("items", "weight", F.explode("items").alias("item"))
        hit = long.join(first, "item").where(F.size(F.array_intersect("items", "itemset")) == F.size("itemset"))
        return hit.groupBy("itemset").agg(F.sum("weight").alias("support_count"))
    got = candidates.select("itemset").toArrow()["itemset"].to_pylist()  # MAX_SENT_CANDIDATES at most
    sent = ranked.sparkSession.sparkContext.broadcast(sorted(got, key=lambda c: (len(c), c)))

    def run(batches):
        sets = sent.value
        total = np.zeros(len(sets), np.int64)
        by_size = {k: np.asarray([c for c in sets if len(c) == k], np.int64) for k in {len(c) for c in sets}}
        for b in batches:
            for lo in range(0, b.num_rows, 512):
                part = b.slice(lo, 512)
                lists = part.column(0)
                x = np.zeros((part.num_rows, n + 1), bool)
                x[pc.list_parent_indices(lists).to_numpy(), pc.list_flatten(lists).to_numpy(zero_copy_only=False)] = True
                weight = part.column(1).to_numpy()
                at = 0
                for k in sorted(by_size):
                    c = by_size[k]
                    for f in range(0, len(c), 4096):
                        some = c[f : f + 4096]
                        hit = x[:, some[:, 0]]
                        for j in range(1, k):
                            hit &= x[:, some[:, j]]
                        total[at + f : at + f + len(some)] += weight @ hit
                    at += len(c)
        ok = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array([sets[i] for i in ok], pa.list_(pa.int32())), pa.array(total[ok])], names=["itemset", "n"])

    return rows.mapInArrow(run, "itemset array<int>, n long").groupBy("itemset").agg(F.sum("n").alias("support_count"))


#: Items of the baskets of one cell, if the number of cells is not given: what a task holds of them.
CELL_ITEMS = 5_000_000


def partitioned(tx: DataFrame, min_support: float, cells: int | None = None, candidate_store: str = "auto", max_len: int | None = None, ledger: CostLedger | None = None, by: str = "hash") -> MiningResult:
    """Cells mined with thresholds of their own; the union of their answers is counted over everything.

    A set that reaches the share in all rows reaches it in a cell at least. Local mining is level by level, as the comparison has it, over a bit for each basket and set.
    Without a number there are as many cells as hold CELL_ITEMS items each, so that a task's memory does not grow with the table.
    """
    prep = prepare(tx, min_support)
    result = MiningResult(prep.ranked, prep.order, prep.min_count, ledger=ledger or CostLedger())
    n_tx = prep.n_tx
    # baskets without a frequent item count for a cell's threshold too: the share is that of the whole
    share = prep.min_count / max(n_tx, 1)
    if cells is None:
        cells = 1 + (prep.ranked.agg(F.coalesce(F.sum(F.size("items")), F.lit(0))).first()[0] // CELL_ITEMS)
    sizes = {r["cell"]: r["count"] for r in by_partition(tx, cells, by).groupBy("cell").count().collect()}  # one row a cell
    result.cells = cells

    def run(t: pa.Table) -> pa.Table:
        lists = t["items"].to_pylist()
        local = max(1, int(np.ceil(share * sizes[t["cell"][0].as_py()] - 1e-9)))
        sets = [s for s, _ in levelwise_local(lists, local, max_len)]
        return pa.table({"itemset": pa.array(sets, pa.list_(pa.int32()))})

    candidates = stage(by_partition(prep.ranked, cells, by).select("cell", "items").groupBy("cell").applyInArrow(run, "itemset array<int>").distinct())
    result.ledger.add("candidates", candidates.count(), candidates.agg(F.coalesce(F.sum(F.size("itemset")), F.lit(0))).first()[0])
    counted = stage(count_candidates(prep.ranked, candidates, prep.n, candidate_store))
    result.candidates = candidates
    return _finish([counted.where(F.col("support_count") >= prep.min_count)], [], prep, result, max_len)


def levelwise_local(lists: list[list[int]], min_count: int, max_len: int | None = None) -> list[tuple[tuple[int, ...], int]]:
    """Level by level within one task: candidates from sets that differ in their last item, cut by their subsets, counted over the rows."""
    rows = Rows.of(lists)
    order = np.argsort(rows.items, kind="stable")
    item, owner = rows.items[order], rows.owner()[order]
    kinds, first = np.unique(item, return_index=True)
    held = {}
    for i, own in zip(kinds.tolist(), np.split(owner, first[1:]), strict=True):
        if len(own) >= min_count:
            x = np.zeros(len(lists), bool)
            x[own] = True
            held[i,] = np.packbits(x)
    count_of = lambda v: int(np.bitwise_count(v).sum())
    out = [(s, count_of(v)) for s, v in held.items()]
    size = 1
    while held and (max_len is None or size < max_len):
        size += 1
        sets = sorted(held)
        known = set(sets)
        new = {}
        for i, a in enumerate(sets):
            for b in sets[i + 1 :]:
                if a[:-1] != b[:-1]:
                    break
                c = (*a, b[-1])
                if size > 2 and any((*c[:k], *c[k + 1 :]) not in known for k in range(size - 2)):
                    continue
                v = held[a] & held[b]
                count = count_of(v)
                if count >= min_count:
                    new[c] = v
                    out.append((c, count))
        held = new
    return out


def levelwise(tx: DataFrame, min_support: float | int, max_len: int | None = None) -> MiningResult:
    """One pass over the database for each size: candidates are joined from the sets one smaller, cut by their subsets, and counted."""
    prep = prepare(tx, min_support)
    result = MiningResult(prep.ranked, prep.order, prep.min_count)
    spark = tx.sparkSession
    level = spark.createDataFrame([([r], c) for r, c in sorted(prep.counts.items())], FI)
    parts, size = [level], 1
    while max_len is None or size < max_len:
        size += 1
        a = level.select(F.slice("itemset", 1, size - 2).alias("head") if size > 2 else F.array().cast("array<int>").alias("head"), F.element_at("itemset", -1).alias("x"))
        joined = a.join(a.withColumnRenamed("x", "y"), "head").where("x < y").select(F.concat("head", F.array("x", "y")).alias("itemset"))
        if size > 2:
            subsets = joined.select("itemset", F.explode(F.transform(F.sequence(F.lit(1), F.lit(size)), lambda k: F.filter("itemset", lambda v, i: i + 1 != k))).alias("sub"))
            alive = subsets.join(level.select(F.col("itemset").alias("sub")), "sub", "left_semi").groupBy("itemset").count().where(F.col("count") == size)
            joined = alive.select("itemset")
        joined = stage(joined)
        if joined.isEmpty():
            break
        level = stage(count_candidates(prep.ranked, joined, prep.n).where(F.col("support_count") >= prep.min_count))
        if level.isEmpty():
            break
        parts.append(level)
    result.passes = size
    return _finish(parts, [], prep, result, max_len)


def sampled(tx: DataFrame, min_support: float, fraction: float, seed: int = 7, slack: float = 0.9, max_len: int | None = None, by: str = "hash") -> MiningResult:
    """Mine a sample with a lowered share, then count what was found over everything. Sets that the sample misses stay missing.

    The sample is those tids whose hash falls in the fraction, so it is the same whatever the partitions; by = "tid" takes the tid's last digit instead.
    """
    prep = prepare(tx, min_support)
    result = MiningResult(prep.ranked, prep.order, prep.min_count)
    in_sample = F.pmod(F.xxhash64(F.lit(seed), "tid"), F.lit(1_000_000)) < int(fraction * 1_000_000) if by == "hash" else F.pmod("tid", F.lit(10)) < round(fraction * 10)
    n_all, n_some = prep.n_tx, tx.where(in_sample).count()
    local = max(1, int(np.ceil(slack * prep.min_count * n_some / max(n_all, 1) - 1e-9))) if fraction < 1 else prep.min_count
    some = encode.collapse(prep.ranked.where(in_sample)).select(F.lit(0).cast("long").alias("group_id"), "items", "weight")
    level = mine_level(some, {0: [*range(1, prep.n + 1)]}, local, max_len=max_len)
    found = _answers(level).select(F.array_sort("itemset").alias("itemset"))
    counted = stage(count_candidates(prep.ranked, found, prep.n))
    result.candidates = found
    return _finish([counted.where(F.col("support_count") >= prep.min_count)], [], prep, result, max_len)


def persisted_tree(tx: DataFrame, min_support: float | int, path: str | None = None, max_len: int | None = None) -> MiningResult:
    """The whole tree as a table on disk, in a folder for each item; each item is mined from its own nodes and their prefixes."""
    import uuid

    prep = prepare(tx, min_support)
    result = MiningResult(prep.ranked, prep.order, prep.min_count)
    path = path or f"{shared_dir(tx.sparkSession)}/tree-{uuid.uuid4().hex}"
    rows = prep.ranked.select("items", F.posexplode("items").alias("p", "item_rank"))
    nodes = rows.select(F.slice("items", F.lit(1), F.col("p") + 1).alias("items"), "item_rank").groupBy("item_rank", "items").agg(F.count(F.lit(1)).alias("weight"))
    nodes.repartition("item_rank").write.mode("overwrite").partitionBy("item_rank").parquet(path)  # a file for each item; its nodes are read by one task anyway
    if prep.n == 0:
        return _finish([], [], prep, result, max_len)
    tree = tx.sparkSession.read.schema("items array<int>, weight long, item_rank int").parquet(path)
    level = mine_level(tree.select(F.col("item_rank").cast("long").alias("group_id"), "items", "weight"), {}, prep.min_count, max_len=max_len, use_array=False)
    _notes(level, result)
    result.tree_path = path
    return _finish([_answers(level)], [], prep, result, max_len)


BLOCK_TIDS = 63


def vertical(tx: DataFrame, min_support: float | int, diffsets: bool = True, max_len: int | None = None) -> MiningResult:
    """Tid lists by column: a set's list is, for each block of 63 baskets, the bits of those that hold it.

    Lists of sets that share all but the last item are joined block by block; with diffsets a set keeps, from pairs on, the bits that its prefix has and it has not.
    """
    prep = prepare(tx, min_support)
    result = MiningResult(prep.ranked, prep.order, prep.min_count)
    spark = tx.sparkSession
    # dense numbers for the tids: a running number within partitions of the hash, joined by partition offsets
    numbered = stage(prep.ranked.select("items", F.monotonically_increasing_id().alias("t")))
    bit = F.expr(f"shiftleft(1L, cast(t % {BLOCK_TIDS} AS int))")
    lists = numbered.select(F.explode("items").alias("r"), F.expr(f"t div {BLOCK_TIDS}").alias("block"), bit.alias("b")).groupBy("r", "block").agg(F.bit_or("b").alias("bits"))
    level = stage(lists.select(F.array().cast("array<int>").alias("head"), F.col("r").alias("last"), "block", "bits"))
    parts = [spark.createDataFrame([([r], c) for r, c in sorted(prep.counts.items())], FI)]
    counts, size = parts[0].withColumn("head", F.array().cast("array<int>")).select("head", F.element_at("itemset", 1).alias("last"), "support_count"), 1
    while max_len is None or size < max_len:
        size += 1
        a, b = level.alias("a"), level.alias("b")
        if diffsets and size > 2:  # what the second lost and the first did not is lost by both together
            pairs = _pairs_of(counts)
            got = pairs.join(level.select("head", F.col("last").alias("y"), "block", F.col("bits").alias("by")), ["head", "y"])
            got = got.join(level.select("head", F.col("last").alias("x"), "block", F.col("bits").alias("bx")), ["head", "x", "block"], "left")
            got = got.select("head", "x", "y", "sx", "block", F.expr("by & ~coalesce(bx, 0L)").alias("bits"))
            lost = got.groupBy("head", "x", "y").agg(F.sum(F.bit_count("bits")).cast("long").alias("lost"))
            support = pairs.join(lost, ["head", "x", "y"], "left").select("head", "x", "y", (F.col("sx") - F.coalesce("lost", F.lit(0))).alias("support_count"))
        else:
            both = a.join(b, (F.col("a.head") == F.col("b.head")) & (F.col("a.block") == F.col("b.block"))).where("a.last < b.last")
            got = both.select(F.col("a.head").alias("head"), F.col("a.last").alias("x"), F.col("b.last").alias("y"), F.col("a.block").alias("block"), F.expr("a.bits & b.bits").alias("bits"), F.col("a.bits").alias("of"))
            support = got.groupBy("head", "x", "y").agg(F.sum(F.bit_count("bits")).cast("long").alias("support_count"))
        support = stage(support.where(F.col("support_count") >= prep.min_count))
        if support.isEmpty():
            break
        parts.append(support.select(F.concat("head", F.array("x", "y")).alias("itemset"), "support_count"))
        keep = got.join(support.select("head", "x", "y"), ["head", "x", "y"], "left_semi")
        if diffsets and size == 2:  # what x has and the pair has not, in every block of x
            xs = level.select(F.col("last").alias("x"), "block", F.col("bits").alias("bx"))
            ys = level.select(F.col("last").alias("y"), "block", F.col("bits").alias("by"))
            keep = support.select("head", "x", "y").join(xs, "x").join(ys, ["y", "block"], "left").select("head", "x", "y", "block", F.expr("bx & ~coalesce(by, 0L)").alias("bits"))
        level = stage(keep.where("bits <> 0").select(F.concat("head", F.array("x")).alias("head"), F.col("y").alias("last"), "block", "bits"))
        counts = support.select(F.concat("head", F.array("x")).alias("head"), F.col("y").alias("last"), "support_count")
    return _finish(parts, [], prep, result, max_len)


def _pairs_of(counts: DataFrame) -> DataFrame:
    """(head, x, y, sx): sets of one head, two at a time, with the first one's count."""
    x = counts.select("head", F.col("last").alias("x"), F.col("support_count").alias("sx"))
    return x.join(counts.select("head", F.col("last").alias("y")), "head").where("x < y")


def brute_force(lists: list[list], min_count: int, max_len: int | None = None) -> dict[tuple, int]:
    """All frequent sets of a few short rows, by listing every subset; for tests."""
    out: dict[tuple, int] = {}
    for items in lists:
        items = sorted(set(items))
        for k in range(1, min(len(items), max_len or len(items)) + 1):
            for s in combinations(items, k):
                out[s] = out.get(s, 0) + 1
    return {s: c for s, c in out.items() if c >= min_count}


def in_memory_rows(lists: list[list[int]], min_count: int, **kw) -> dict[tuple[int, ...], int]:
    return {tuple(sorted(s)): c for s, c in mine_all(Rows.of(lists), min_count, **kw)}


__all__ = ["brute_force", "count_candidates", "exploded", "in_memory", "in_memory_rows", "levelwise", "levelwise_local", "partitioned", "per_item_projection", "persisted_tree", "sampled", "vertical"]
