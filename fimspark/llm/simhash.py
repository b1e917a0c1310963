"""SimHash near-duplicates by vantage-point trees.

Fingerprints: XXH64 (seed 42) of each 3-word shingle; a bit is set if it is in over half of them. Texts are
fingerprinted whole in map tasks; equal fingerprints then count as one point with its least doc_id.

Points within REACH differing bits link. The top of a vantage-point tree is fitted on a bounded sample of points:
each inner node has a vantage point and a radius, and points nearer than the radius go inside, the others outside. Every
point is stored in the one shard that it falls in. As a query it also visits the far side of each node whose boundary is within REACH
of it (triangle bound); of two points on both sides of a node only the inner one crosses, so each pair meets exactly once.
Each shard builds a tree of its own and answers its queries in it. What comes out of a shard is at most one link for each
point and query there (a spanning forest of the links found), never all pairs of a group. Components are then found over all shards.

A shard whose points are too close together for a tree (more than DENSE in one leaf) looks up all 2,080 keys within two bits of each query in a sorted array instead, which is exact too.

A text without words (null, empty) has fingerprint zero and links like any other. A null doc_id is kept in no link and gets itself (null) as component.
Repeated rows share a component. Empty tables give no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, pick, table
from .components import components

SEED, WORDS, REACH = 42, 3, 2
#: Points in a shard, points in a leaf of a shard's tree, and the sample that the tree over the shards is fitted on.
SHARD, LEAF, SAMPLE = 4000, 48, 200_000
DENSE = 4096


def fingerprint(text: str | None, words: int = WORDS) -> int:
    from xxhash import xxh64_intdigest

    parts = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not parts:
        return 0
    joined = b" ".join(parts)
    if len(parts) <= words:
        h = np.asarray([xxh64_intdigest(joined, SEED)], np.uint64)
    else:
        ends = np.cumsum([len(p) + 1 for p in parts])
        first = np.concatenate([[0], ends[:-words]]).tolist()
        last = (ends[words - 1 :] - 1).tolist()
        h = np.asarray([xxh64_intdigest(joined[a:b], SEED) for a, b in zip(first, last, strict=True)], np.uint64)
    counts = np.zeros(64, np.int64)
    for lo in range(0, len(h), 4096):
        counts += np.unpackbits(h[lo : lo + 4096].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits((2 * counts > len(h)).astype(np.uint8), bitorder="little").view(np.uint64)[0])


def _signed(x: np.ndarray) -> np.ndarray:
    return x.astype(np.uint64).view(np.int64)


def _fingerprints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        yield pa.RecordBatch.from_arrays([b.column(0), pa.array(_signed(np.asarray([fingerprint(t.as_py()) for t in b.column(1)], np.uint64)))], names=["doc_id", "fp"])


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id, fp: the fingerprint's 64 bits as a long."""
    return pick(docs, "doc_id", "text").selectExpr("cast(doc_id as long) doc_id", "cast(text as string) text").mapInArrow(_fingerprints, "doc_id long, fp long")


def distance(a: np.ndarray, b) -> np.ndarray:
    return np.bitwise_count(a ^ b)


class Tree:
    """A vantage-point tree as flat arrays; a leaf has radius -1 and its number as outside."""

    def __init__(self, points: np.ndarray, leaf: int):
        self.vantage: list[np.uint64] = []
        self.radius: list[int] = []
        self.inside: list[int] = []
        self.outside: list[int] = []
        self.leaves: list[np.ndarray] = []
        todo = [(np.arange(len(points)), -1, False)]
        while todo:
            rows, parent, inner = todo.pop()
            node = len(self.vantage)
            if parent >= 0:
                (self.inside if inner else self.outside)[parent] = node
            split = self._split(points, rows) if len(rows) > leaf else None
            self.vantage.append(points[split[0]] if split else np.uint64(0))
            self.radius.append(split[1] if split else -1)
            self.inside.append(-1)
            self.outside.append(-1 if split else len(self.leaves))
            if split:
                todo += [(rows[~split[2]], node, False), (rows[split[2]], node, True)]
            else:
                self.leaves.append(rows)

    @staticmethod
    def _split(points: np.ndarray, rows: np.ndarray):
        """Of a few vantage points, the one that leaves the least on the larger side, boundary included; None if all leave nearly everything."""
        best = None
        for v in rows[:: max(1, len(rows) // 6)][:6]:
            d = distance(points[rows], points[v]).astype(np.int64)
            r = int(np.median(d))
            for radius in (r, r + 1):
                inside = d < radius
                n = int(inside.sum())
                crossing = int((inside & (d >= radius - REACH)).sum())
                worth = max(n, len(rows) - n + crossing)
                if min(n, len(rows) - n) * 64 >= len(rows) and (best is None or worth < best[0]):
                    best = (worth, v, radius, inside)
        return best and best[1:]

    def route(self, points: np.ndarray, stored: bool) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """(leaf, rows, stored there) for each leaf that points belong to (if they are to be stored) or have to ask."""
        todo = [(0, np.arange(len(points)), np.full(len(points), stored))]
        while todo:
            node, rows, home = todo.pop()
            if not len(rows):
                continue
            r = self.radius[node]
            if r < 0:
                yield self.outside[node], rows, home
                continue
            d = distance(points[rows], self.vantage[node]).astype(np.int64)
            inner = d < r
            to_in = np.where(home, inner, d < r + REACH)
            to_out = d >= r - REACH
            todo.append((self.inside[node], rows[to_in], home[to_in]))
            todo.append((self.outside[node], rows[to_out], (home & ~inner)[to_out]))


def _ball(reach: int) -> np.ndarray:
    """All differences of at most reach bits."""
    out = [0]
    for k in range(1, reach + 1):
        out += [sum(1 << b for b in bits) for bits in combinations(range(64), k)]
    return np.asarray(out, np.uint64)


def shard_links(points: np.ndarray, stored: np.ndarray, leaf: int = LEAF, dense: int = DENSE) -> list[tuple[int, int]]:
    """Row pairs that connect all that links among the stored points, and between the other points and the stored ones."""
    home, others = np.flatnonzero(stored), np.flatnonzero(~stored)
    out: list[tuple[int, int]] = []
    if not len(home):
        return out
    parent = np.arange(len(points))

    def join(rows: np.ndarray) -> None:
        root = parent[rows]
        while (parent[root] != root).any():
            root = parent[root]
        root = np.unique(root)
        if len(root) > 1:
            out.extend((int(x), int(root[0])) for x in root[1:])
            parent[root] = root[0]

    tree = Tree(points[home], leaf)
    ball = None
    for rows_of, flag in ((home, True), (others, False)):
        for k, rows, _ in tree.route(points[rows_of], flag):
            rows, there = rows_of[rows], home[tree.leaves[k]]
            if len(there) > dense:
                ball = _ball(REACH) if ball is None else ball
                order = there[np.argsort(points[there], kind="stable")]
                keys = points[order]
                for q in rows:
                    want = ball ^ points[q]
                    i = np.minimum(np.searchsorted(keys, want), len(keys) - 1)
                    join(np.append(order[i[keys[i] == want]], q))
                continue
            for lo in range(0, len(rows), 256):
                part = rows[lo : lo + 256]
                near = distance(points[part][:, None], points[there][None, :]) <= REACH
                own = np.isin(part, there, assume_unique=False).astype(np.int64)
                for i in np.flatnonzero(near.sum(axis=1) > own):
                    join(np.append(there[near[i]], part[i]))
    return out


def _links(t: pa.Table) -> pa.Table:
    points = np.asarray(t["fp"].to_numpy(), np.int64).view(np.uint64)
    node = t["node"].to_numpy()
    pairs = np.asarray(shard_links(points, np.asarray(t["stored"].to_pylist(), bool)), np.int64).reshape(-1, 2)
    return pa.table({"a": pa.array(node[pairs[:, 0]], pa.int64()), "b": pa.array(node[pairs[:, 1]], pa.int64())})


def links(points: DataFrame, shard: int = SHARD, sample: int = SAMPLE) -> DataFrame:
    """points: fp (distinct), node. Returns a, b: nodes that are linked, enough to connect all that link."""
    n = points.count()
    some = points.select("fp").orderBy(F.xxhash64("fp"), "fp").limit(sample).toArrow()["fp"].to_numpy()  # sample * 8 bytes
    fitted = np.asarray(some, np.int64).view(np.uint64)
    tree = points.sparkSession.sparkContext.broadcast(Tree(fitted, max(8, int(len(fitted) * shard / max(n, 1)))))

    def route(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp, node = b.column(0).to_numpy(), b.column(1).to_numpy()
            for k, rows, home in tree.value.route(fp.view(np.uint64), True):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(rows), k, np.int64)), pa.array(fp[rows]), pa.array(node[rows]), pa.array(home)], names=["shard", "fp", "node", "stored"])

    routed = points.select("fp", "node").mapInArrow(route, "shard long, fp long, node long, stored boolean")
    return routed.groupBy("shard").applyInArrow(_links, "a long, b long")


def near_duplicates(docs: DataFrame) -> DataFrame:
    """doc_id, fp (long), component_id of each document."""
    f = cut(fingerprints(docs))
    points = cut(f.where("doc_id is not null").groupBy("fp").agg(F.min("doc_id").alias("node")))
    found = components(links(points))
    named = points.join(found, "node", "left").select("fp", F.coalesce("component", "node").alias("component_id"))
    out = f.join(named, "fp", "left")
    return out.select("doc_id", "fp", F.when(F.col("doc_id").isNotNull(), F.col("component_id")).alias("component_id"))


def op3_simhash(spark, sf_dir) -> DataFrame:
    out = near_duplicates(table(spark, sf_dir, "documents"))
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
