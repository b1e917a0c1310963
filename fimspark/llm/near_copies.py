"""Near copies by SimHash fingerprints in vantage-point trees, and exact similarity of word shingles.

A text's set is the XXH64 (seed 42) of each of its runs of WORDS words; texts of fewer words are one run. Documents whose sets have a Jaccard similarity of
LEAST or more link. Equal sets count as one point with its least doc_id.

Texts of similarity 0.8 lie 6 to 14 of 64 bits apart, and at such a reach a tree of whole fingerprints prunes nothing. So fingerprints are longer, a majority of shingles' bits
as in `simhash`, and are cut: CHECK words and BLOCKS blocks of BITS bits. Each block has its own vantage-point tree, dealt to shards with the points within
`simhash.REACH` bits of a boundary crossing it, as there. A bit of two sets of similarity 0.8 differs with a chance of 0.152 at most; they are within two bits in a block with 0.27 and so miss each
other in all trees with 1.4e-9 (a set of 4 shingles and one of 5, where majorities tie, with 4e-5). Points that meet are candidates if their check words differ in at most FAR bits (a pair at 0.8 is lost so with 1.3e-6,
sets of 4 and 5 with 9e-6 for their own bound) and their sizes allow the similarity. What is left is compared exactly, in two rounds:

1. Each point with the most similar of its leaders (in each shard, its least candidate). A leader's points are dealt to groups of GROUP.
2. Components that candidates connect (a spanning forest of these is enough) form blocks. They are searched by lists of the sets that hold a shingle, for points outside the largest component.

Above the trees, points are cut by the sizes of their sets (their distance from the empty set, which costs fewer crossings than other vantage points), if these differ enough. Shards hold about SHARD points, and blocks are looked at in pairs of chunks of about VOLUME shingles, so no task holds a whole tree, block or component,
and nowhere are the pairs of a group listed. Links become components by rounds of joins.

Null doc_ids are in no link. Texts without words have the empty set and are one point. Empty tables give no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import simhash
from .common import cut, pick
from .components import components

SEED, WORDS = 42, 5
#: Similarity from which documents link, as a fraction of integers.
LEAST = (4, 5)
BLOCKS, BITS, CHECK, WIDE = 64, 24, 2, 26
FAR, FAR_SMALL, SMALL = 40, 44, 5
#: Points of a leader that are verified at once, rows that are compared with LEAF points at once, and shingles in a chunk of a block.
GROUP, CHUNK, VOLUME = 500, 4000, 1_000_000
#: Points in a shard of a block's tree, points in a leaf, points that the tree over a block's shards is fitted on, and points in a leaf that no vantage point splits.
SHARD, LEAF, SAMPLE, DENSE = 500_000, 128, 4000, 4096
_STEPS = np.arange(WIDE, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)


def shingles(text: str | None, words: int = WORDS) -> np.ndarray:
    """The set as sorted distinct hashes."""
    from xxhash import xxh64_intdigest

    parts = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not parts:
        return np.zeros(0, np.uint64)
    joined = b" ".join(parts)
    ends = np.cumsum([len(p) + 1 for p in parts])
    first = np.concatenate([[0], ends[:-words]]).tolist()
    last = (ends[words - 1 :] - 1).tolist() if len(parts) > words else [len(joined)]
    return np.unique(np.asarray([xxh64_intdigest(joined[a:b], SEED) for a, b in zip(first, last)], np.uint64))


def fingerprint(s: np.ndarray) -> np.ndarray:
    """WIDE words, each bit set if over half of the set's have it; the first word is of the shingles' hashes themselves, the others of hashes of them."""
    counts = np.zeros(64 * WIDE, np.int64)
    for lo in range(0, len(s), 255):
        z = s[lo : lo + 255, None] + _STEPS
        z[:, 1:] = (z[:, 1:] ^ (z[:, 1:] >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        z[:, 1:] = (z[:, 1:] ^ (z[:, 1:] >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        z[:, 1:] ^= z[:, 1:] >> np.uint64(31)
        counts += np.unpackbits(z.view(np.uint8), axis=1, bitorder="little").sum(axis=0, dtype=np.uint8)
    return np.packbits((2 * counts > len(s)).astype(np.uint8), bitorder="little").view(np.uint64)


def blocks(words: np.ndarray) -> np.ndarray:
    """Fingerprints' blocks: a row for each fingerprint, a column for each block."""
    b = np.ascontiguousarray(words[:, CHECK:]).view(np.uint8).reshape(len(words), BLOCKS, BITS // 8).astype(np.uint64)
    return b[:, :, 0] | b[:, :, 1] << np.uint64(8) | b[:, :, 2] << np.uint64(16)


def _keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    from xxhash import xxh128_digest

    for b in batches:
        sets = [shingles(t.as_py()) for t in b.column(1)]
        yield pa.RecordBatch.from_arrays(
            [
                b.column(0),
                pa.array([xxh128_digest(s.tobytes()) for s in sets], pa.binary()),
                pa.array([len(s) for s in sets], pa.int64()),
                pa.array([fingerprint(s).view(np.int64) for s in sets], pa.list_(pa.int64())),
            ],
            names=["doc_id", "same", "n", "fp"],
        )


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        yield pa.RecordBatch.from_arrays([b.column(0), pa.array([shingles(t.as_py()).tobytes() for t in b.column(1)], pa.binary())], names=["node", "shingles"])


def _verified(t: pa.Table) -> pa.Table:
    """A leader and some points: those that are similar enough."""
    lead, node = t["lead"][0].as_py(), t["node"].to_numpy()
    sets = [np.frombuffer(x, np.uint64) for x in t["shingles"].to_pylist()]
    part, whole = LEAST
    out = set()
    for own in (sets[k] for k in np.flatnonzero(node == lead)):
        for k in np.flatnonzero(node != lead):
            at = np.minimum(np.searchsorted(own, sets[k]), max(len(own) - 1, 0))
            shared = int((own[at] == sets[k]).sum()) if len(own) else 0
            # s / (a + b - s) >= part / whole
            if (part + whole) * shared >= part * (len(own) + len(sets[k])) > 0:
                out.add(int(node[k]))
    return pa.table({"a": pa.array(sorted(out), pa.int64()), "b": pa.array([lead] * len(out), pa.int64())})


def verify(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """pairs: node, lead (distinct); sets: node, shingles. The pairs that are similar enough, as a, b."""
    many = pairs.groupBy("lead").agg(F.ceil(F.count(F.lit(1)) / GROUP).cast("long").alias("parts"))
    dealt = pairs.join(many, "lead").select("lead", F.expr("pmod(xxhash64(node), parts)").alias("part"), "node")
    leads = many.select("lead", F.explode(F.expr("sequence(0L, parts - 1)")).alias("part"), F.col("lead").alias("node"))
    held = dealt.unionByName(leads).join(sets, "node").select("lead", "part", "node", "shingles")
    return cut(held.groupBy("lead", "part").applyInArrow(_verified, "a long, b long"))


def _words(column: pa.ChunkedArray | pa.Array) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return np.asarray(column.flatten().to_numpy(), np.int64).view(np.uint64).reshape(len(column), -1)


class Candidates:
    """The candidates that points of a shard meet: for each point the least of them, and a spanning forest. Points are in the order of their nodes."""

    def __init__(self, check: np.ndarray, size: np.ndarray):
        self.check, self.size = check, size
        self.parent = np.arange(len(size))
        self.least = np.arange(len(size))
        self.forest: list[np.ndarray] = []

    def distance(self, i, j) -> np.ndarray:
        return np.bitwise_count(self.check[i] ^ self.check[j]).sum(axis=-1, dtype=np.int64)

    def near(self, i, j) -> np.ndarray:
        low, high = np.minimum(self.size[i], self.size[j]), np.maximum(self.size[i], self.size[j])
        part, whole = LEAST
        return (self.distance(i, j) <= np.where(high <= SMALL, FAR_SMALL, FAR)) & (whole * low >= part * high)

    def pairs(self) -> tuple[np.ndarray, np.ndarray]:
        """Each point with its least candidate, and the pairs that connect what these leave apart."""
        own = np.flatnonzero(self.least != np.arange(len(self.size)))
        leads, rest = np.column_stack([own, self.least[own]]), Candidates(self.check, self.size)
        rest.add(*leads.T)
        rest.forest = []
        for x in self.forest:
            rest.add(*x.T)
        return leads, np.concatenate([np.zeros((0, 2), np.int64), *rest.forest])

    def roots(self, rows: np.ndarray) -> np.ndarray:
        root = self.parent[rows]
        while (self.parent[root] != root).any():
            root = self.parent[root]
        self.parent[rows] = root
        return root

    def add(self, i: np.ndarray, j: np.ndarray) -> None:
        """Pairs of candidates."""
        i, j = np.maximum(i, j), np.minimum(i, j)
        np.minimum.at(self.least, i, j)
        while len(i):
            a, b = self.roots(i), self.roots(j)
            live = a != b
            i, j, a, b = i[live], j[live], a[live], b[live]
            high, first = np.unique(np.maximum(a, b), return_index=True)
            self.parent[high] = np.minimum(a, b)[first]
            self.forest.append(np.column_stack([i[first], j[first]]))

    def meet(self, rows: np.ndarray, there: np.ndarray, key: np.ndarray) -> None:
        """All of rows with all of there, by blocks first."""
        step = max(1, CHUNK * LEAF // len(there))
        for lo in range(0, len(rows), step):
            i, j = np.nonzero(np.bitwise_count(key[rows[lo : lo + step], None] ^ key[there]) <= simhash.REACH)
            i, j = rows[lo + i], there[j]
            i, j = i[i != j], j[i != j]
            close = self.near(i, j)
            if close.any():
                self.add(i[close], j[close])

    def spread(self, rows: np.ndarray) -> None:
        """All that chains of candidates connect, whatever their blocks: a point that was found is looked for no more."""
        left = np.sort(rows)
        while len(left):
            todo, left = [left[0]], left[1:]
            while todo and len(left):
                k = todo.pop()
                close = self.near(left, k)
                found, left = left[close], left[~close]
                todo += found.tolist()
                self.add(found, np.full(len(found), k))


def candidates(key: np.ndarray, check: np.ndarray, size: np.ndarray, stored: np.ndarray, leaf: int | None = None, dense: int | None = None) -> Candidates:
    """Of points in the order of their nodes: candidates among the stored ones, and of the others with them."""
    out = Candidates(check, size)
    home, others = np.flatnonzero(stored), np.flatnonzero(~stored)
    if not len(home):
        return out
    tree = simhash.Tree(key[home], LEAF if leaf is None else leaf)
    short = key.astype(np.uint32)
    for k, rows in ((k, own[rows]) for own, flag in ((home, True), (others, False)) for k, rows, _ in tree.route(key[own], flag)):
        there = home[tree.leaves[k]]
        if len(there) > (DENSE if dense is None else dense):
            out.spread(np.union1d(rows, there))
        else:
            out.meet(rows, there, short)
    return out


def _shard(t: pa.Table) -> pa.Table:
    t = t.sort_by("node")
    check = np.column_stack([t[f"c{k}"].to_numpy().view(np.uint64) for k in range(CHECK)])
    node = t["node"].to_numpy()
    found = candidates(t["key"].to_numpy().astype(np.uint64), check, t["n"].to_numpy().astype(np.int64), np.asarray(t["stored"].to_numpy(), bool))
    leads, rest = found.pairs()
    pairs = np.concatenate([leads, rest])
    far = found.distance(pairs[:, 0], pairs[:, 1])
    return pa.table({"a": pa.array(node[pairs[:, 0]]), "b": pa.array(node[pairs[:, 1]]), "far": pa.array(far), "lead": pa.array(np.arange(len(pairs)) < len(leads))})


def size_bounds(sizes: np.ndarray, parts: int) -> np.ndarray:
    """Sizes that cut a sample into at most so many levels, each bound so far over the one before that no two similar sets have two bounds between them."""
    part, whole = LEAST
    out: list[int] = []
    for s in np.sort(sizes)[[len(sizes) * k // parts for k in range(1, parts)]].tolist() if len(sizes) else []:
        if s > int(sizes.min()) and (not out or part * s >= whole * out[-1]):
            out.append(s)
    return np.asarray(out, np.int64)


def by_size(size: np.ndarray, bounds: np.ndarray) -> Iterator[tuple[int, np.ndarray, bool]]:
    """(level, rows, stored there): each point's own level, and the next if its bound is within reach."""
    part, whole = LEAST
    level = np.searchsorted(bounds, size, "right")
    for c in range(len(bounds) + 1):
        if (own := np.flatnonzero(level == c)).size:
            yield c, own, True
        if c and (below := np.flatnonzero((level == c - 1) & (whole * size >= part * bounds[c - 1]))).size:
            yield c, below, False


def near_pairs(points: DataFrame) -> DataFrame:
    """points: node, n, fp. Distinct candidates a > b: of each point its leaders (lead), and enough to connect all that candidates connect."""
    n = points.count()
    some = points.select("fp", "n").orderBy(F.xxhash64("fp"), "fp").limit(SAMPLE).toArrow()  # 8 * WIDE bytes each
    fitted, sizes = (blocks(_words(some["fp"])) if len(some) else np.zeros((0, BLOCKS), np.uint64)), some["n"].to_numpy()
    leaf, bounds = max(8, int(len(fitted) * SHARD / max(n, 1))), size_bounds(sizes, -(-n // SHARD))
    level = np.searchsorted(bounds, sizes, "right")
    trees = points.sparkSession.sparkContext.broadcast([[simhash.Tree(fitted[level == c, k], leaf) for k in range(BLOCKS)] for c in range(len(bounds) + 1)])

    def route(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            words, node, size = _words(b.column(2)) if b.num_rows else None, b.column(0).to_numpy(), b.column(1).to_numpy()
            for c, rows, stored in by_size(size, bounds):
                key, check, own, many = blocks(words[rows]), words[rows, :CHECK].view(np.int64), node[rows], size[rows].astype(np.int32)
                for k, tree in enumerate(trees.value[c]):
                    for at, to, home in tree.route(key[:, k], stored):
                        yield pa.RecordBatch.from_arrays(
                            [
                                pa.array(np.full(len(to), (c * BLOCKS + k) << 32 | at, np.int64)),
                                pa.array(key[to, k].astype(np.int32)),
                                *(pa.array(check[to, x]) for x in range(CHECK)),
                                pa.array(own[to]),
                                pa.array(many[to]),
                                pa.array(home),
                            ],
                            names=["shard", "key", *(f"c{x}" for x in range(CHECK)), "node", "n", "stored"],
                        )

    schema = "shard long, key int, " + "".join(f"c{c} long, " for c in range(CHECK)) + "node long, n int, stored boolean"
    met = points.select("node", "n", "fp").mapInArrow(route, schema).groupBy("shard").applyInArrow(_shard, "a long, b long, far long, lead boolean")
    return cut(met.where("a <> b").groupBy("a", "b").agg(F.min("far").alias("far"), F.max("lead").alias("lead")))


def linked(sets: list[np.ndarray], comp: np.ndarray, chunk: np.ndarray) -> list[tuple[int, int]]:
    """Pairs of similar sets of different components (and chunks, if there are two), enough to connect all components that such pairs connect."""
    part, whole = LEAST
    size = np.asarray([len(s) for s in sets], np.int64)
    kinds, of, many = np.unique(comp, return_inverse=True, return_counts=True)
    two = len(np.unique(chunk)) > 1
    _, code = np.unique(np.concatenate(sets), return_inverse=True)
    codes = np.split(code, np.cumsum(size)[:-1])
    order = np.argsort(code, kind="stable")
    holds = np.repeat(np.arange(len(sets)), size)[order]
    starts = np.searchsorted(code[order], np.arange(int(code.max(initial=-1)) + 2))
    group, out = np.arange(len(kinds)), []
    for k in np.flatnonzero(of != many.argmax()).tolist():
        other = group[of] != group[of[k]]
        if two:
            other &= chunk != chunk[k]
        if not other.any() or not size[k]:
            continue
        shared = np.bincount(np.concatenate([holds[starts[c] : starts[c + 1]] for c in codes[k]]), minlength=len(sets))
        # s / (a + b - s) >= part / whole
        for i in np.flatnonzero(other & ((part + whole) * shared >= part * (size + size[k]))).tolist():
            if group[of[i]] != group[of[k]]:
                group[group == group[of[i]]] = group[of[k]]
                out.append((k, i))
    return out


def _searched(t: pa.Table) -> pa.Table:
    """A block's chunk, or two of its chunks."""
    node = t["node"].to_numpy()
    pairs = np.asarray(linked([np.frombuffer(x, np.uint64) for x in t["shingles"].to_pylist()], t["comp"].to_numpy(), t["chunk"].to_numpy()), np.int64).reshape(-1, 2)
    return pa.table({"a": pa.array(node[pairs[:, 0]], pa.int64()), "b": pa.array(node[pairs[:, 1]], pa.int64())})


def _in_chunks(df: DataFrame, *keep: str) -> DataFrame:
    """Rows with a number of chunks: dealt to all pairs of chunks (i, j) that theirs is one of."""
    dealt = df.withColumn("chunk", F.expr("pmod(xxhash64(node), chunks)")).withColumn("k", F.explode(F.expr("sequence(0L, chunks - 1)")))
    return dealt.select(*keep, F.least("chunk", "k").alias("i"), F.greatest("chunk", "k").alias("j"), "chunk")


def near_copies(docs: DataFrame) -> DataFrame:
    """doc_id, component_id of each document: the least doc_id that links lead to."""
    rows = pick(docs, "doc_id", "text").selectExpr("cast(doc_id as long) doc_id", "cast(text as string) text").where("doc_id is not null")
    f = cut(rows.mapInArrow(_keys, "doc_id long, same binary, n long, fp array<long>"))
    points = cut(f.groupBy("same").agg(F.min("doc_id").alias("node"), F.first("n").alias("n"), F.first("fp").alias("fp")))
    near = near_pairs(points.where("n > 0"))
    ends = cut(near.select(F.explode(F.array("a", "b")).alias("node")).distinct())
    # only points with a candidate are ever compared; their sets are made once, and both rounds read them where they are
    sets = cut(rows.join(ends.withColumnRenamed("node", "doc_id"), "doc_id", "left_semi").mapInArrow(_sets, "node long, shingles binary"))
    best = near.where("lead").groupBy("a").agg(F.min(F.struct("far", "b")).alias("x")).select(F.col("a").alias("node"), F.col("x.b").alias("lead"))
    links = verify(best, sets)
    found = components(links)

    named = cut(ends.join(found, "node", "left").select("node", F.coalesce("component", "node").alias("comp")))
    across = near.join(named.toDF("a", "c"), "a").join(named.toDF("b", "d"), "b").where("c <> d").select(F.col("c").alias("a"), F.col("d").alias("b")).distinct()
    members = cut(named.join(components(across).toDF("comp", "block"), "comp").select("node", "block", "comp"))
    if not members.isEmpty():
        size = points.groupBy("node").agg(F.sum("n").alias("n"))
        volume = members.join(size, "node").groupBy("block").agg(F.ceil(F.sum("n") / VOLUME).cast("long").alias("chunks"))
        held = members.join(volume, "block").join(sets, "node")
        links = links.unionByName(cut(_in_chunks(held, "block", "node", "comp", "shingles").groupBy("block", "i", "j").applyInArrow(_searched, "a long, b long")))
        found = components(links)
    by_set = points.select("same", "node").join(found, "node", "left").select("same", F.coalesce("component", "node").alias("component_id"))
    return f.select("doc_id", "same").join(by_set, "same").select("doc_id", "component_id")
