"""Benchmark decontamination by q-gram counting in diagonal bands and banded alignment.

Benchmark texts and documents are compared as UTF-8 bytes with A-Z in lower case and white space as single spaces. Any passage of SEGMENT bytes of an
item (the whole item if shorter) leaks into a document if a region of the document can be turned into it by at most EDITS of its length in edits.
Such a region and the passage share at least SEGMENT - Q + 1 - Q * edits grams of Q bytes, all on diagonals that lie no further apart than the edits.
So the shared grams of a document and an item are counted in overlapping bands of diagonals (each band twice as wide as needed, so that any such set lies
within one), and runs of a band that reach the count within a passage's reach are kept. Each start in the item whose passage holds all grams of such a run is
verified by banded alignment against the region; one start of each document and item is tried first, and all of them where that fails. No passage within the edits is lost.

Items are the small side: their grams are sent to all tasks if they have at most MAX_INDEX_BYTES; a larger benchmark is handled in as many passes over the documents as it takes.
A window that meets no gram costs nothing more, whatever the document's length.

Null or empty texts, and items shorter than MIN_ITEM bytes, match nothing. Repeated documents and items are each reported. Empty tables give no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import pick, table

Q, SEGMENT, MIN_ITEM = 8, 64, 24
EDITS = 0.08
#: Bytes of items in one index, which takes about 22 times as much in each worker.
MAX_INDEX_BYTES = 4 << 20
#: Bytes of documents that are searched at once.
CHUNK = 2 << 20
#: Alignments done at once.
SIDE_BY_SIDE = 16_384
_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[65:91] += 32
_FOLD[[9, 10, 11, 12, 13]] = 32


def fold(raw: bytes) -> bytes:
    """A-Z in lower case, runs of ASCII white space as one space, none at the ends."""
    x = _FOLD[np.frombuffer(raw, np.uint8)]
    if not len(x):
        return b""
    space = x == 32
    keep = ~space
    keep[:-1] |= space[:-1] & ~space[1:]
    return x[keep].tobytes().strip(b" ")


def grams(data: bytes) -> np.ndarray:
    """Each window of Q = 8 bytes as one number."""
    x = np.frombuffer(data, np.uint8)
    if len(x) < Q:
        return np.zeros(0, np.uint64)
    return np.lib.stride_tricks.sliding_window_view(x, Q).copy().view(np.uint64).ravel()


def budget(length: int) -> int:
    return int(EDITS * length)


def needed(length: int) -> int:
    return max(1, length - Q + 1 - Q * budget(length))


def edit_distance_within(passage: bytes, region: bytes, k: int) -> bool:
    """Whether some part of region is at most k edits from passage.

    Columns of the whole passage for each byte of the region; start and end in the region are free. Bits of one long
    number hold the vertical differences, so that a column costs a few operations.
    """
    m = len(passage)
    if not m:
        return True
    where: dict[int, int] = {}
    for i, c in enumerate(passage):
        where[c] = where.get(c, 0) | 1 << i
    ones, top = (1 << m) - 1, 1 << (m - 1)
    up, down, score = ones, 0, m
    for c in region:
        eq = where.get(c, 0)
        vertical = eq | down
        diagonal = (((eq & up) + up) ^ up) | eq
        h_up = down | (ones & ~(diagonal | up))
        h_down = up & diagonal
        score += bool(h_up & top) - bool(h_down & top)
        if score <= k:
            return True
        h_up, h_down = h_up << 1 & ones, h_down << 1 & ones
        up, down = h_down | (ones & ~(vertical | h_up)), h_up & vertical
    return False


def within(passages: np.ndarray, sizes: np.ndarray, regions: np.ndarray, reach: np.ndarray, k: np.ndarray) -> np.ndarray:
    """For each row, whether some part of the region (its first `reach` bytes) is at most k edits from the passage (its first `sizes` bytes, 64 at most).

    As edit_distance_within, for many rows at once: a passage's column is one machine word.
    """
    n = len(passages)
    wide = np.zeros((n, 64), np.uint8)
    wide[:, : passages.shape[1]] = passages
    bit = np.uint64(1) << (sizes - 1).astype(np.uint64)
    ones = bit | (bit - np.uint64(1))
    up, down, score = ones.copy(), np.zeros(n, np.uint64), sizes.astype(np.int64)
    best = score.copy()
    one = np.uint64(1)
    for j in range(int(reach.max(initial=0))):
        eq = np.packbits(wide == regions[:, j : j + 1], axis=1, bitorder="little").view(np.uint64).ravel() & ones
        eq[j >= reach] = 0
        vertical = eq | down
        diagonal = (((eq & up) + up) ^ up) | eq
        h_up = down | ~(diagonal | up)
        h_down = up & diagonal
        score += (h_up & bit != 0).astype(np.int64) - (h_down & bit != 0)
        best = np.where(j < reach, np.minimum(best, score), best)
        h_up, h_down = h_up << one, h_down << one
        up, down = h_down | ~(vertical | h_up), h_up & vertical
    return best <= k


class Index:
    """The grams of some items, sorted, with a bitmap in front."""

    BITS = 20

    def __init__(self, items: list[tuple[int, bytes]]):
        self.ids = np.asarray([i for i, _ in items], np.int64)
        texts = [t for _, t in items]
        self.raw = np.frombuffer(b"".join(texts) + b"\0", np.uint8)
        self.sizes = np.asarray([len(t) for t in texts], np.int64)
        self.begins = np.cumsum(self.sizes) - self.sizes
        g = [grams(t) for t in texts]
        code = np.concatenate([*g, np.zeros(0, np.uint64)])
        item = np.repeat(np.arange(len(g)), [len(x) for x in g])
        pos = np.concatenate([*(np.arange(len(x)) for x in g), np.zeros(0, np.int64)])
        order = np.argsort(code, kind="stable")
        code, self.item, self.pos = code[order], item[order].astype(np.int32), pos[order].astype(np.int32)
        self.codes, self.first = np.unique(code, return_index=True)
        self.last = np.append(self.first[1:], len(code))
        self.bitmap = np.zeros(1 << self.BITS, bool)
        self.bitmap[self._at(self.codes)] = True
        self.least = np.asarray([needed(min(SEGMENT, len(t))) for t in texts], np.int64)
        self.edits = np.asarray([budget(min(SEGMENT, len(t))) for t in texts], np.int64)
        self.longest = max([len(t) for t in texts], default=0)
        self.band = max(2, 1 + budget(SEGMENT))

    def _at(self, codes: np.ndarray) -> np.ndarray:
        return ((codes * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.BITS)).astype(np.int64)

    def search(self, texts: list[bytes]) -> list[tuple[int, int]]:
        """(text, item) pairs that leak; the texts are folded and joined by bytes that no item has."""
        lengths = np.asarray([len(t) for t in texts], np.int64)
        start = np.cumsum(lengths + Q) - lengths - Q
        joined = (b"\0" * Q).join(texts)
        g = grams(joined)
        at = np.flatnonzero(self.bitmap[self._at(g)])
        if not len(at) or not len(self.codes):
            return []
        k = np.minimum(np.searchsorted(self.codes, g[at]), len(self.codes) - 1)
        hit = self.codes[k] == g[at]
        at, k = at[hit], k[hit]
        n = self.last[k] - self.first[k]
        total = int(n.sum())
        if not total:
            return []
        pos = np.repeat(at, n)
        entry = np.repeat(self.first[k] - (np.cumsum(n) - n), n) + np.arange(total)
        item, own = self.item[entry].astype(np.int64), self.pos[entry].astype(np.int64)
        # documents that share too few grams with an item in all go no further
        doc = np.searchsorted(start, pos, side="right") - 1
        _, which, many = np.unique(doc * len(self.ids) + item, return_inverse=True, return_counts=True)
        enough = many[which] >= self.least[item]
        pos, item, own, doc = pos[enough], item[enough], own[enough], doc[enough]
        # bands twice as wide as their distance: each diagonal is in two
        band = (pos - own + self.longest) // self.band
        n_bands = (len(joined) + self.longest) // self.band + 2
        group = np.concatenate([item * n_bands + band, item * n_bands + band + 1])
        key = np.lexsort((np.tile(pos, 2), group))
        both = np.tile(np.arange(len(pos)), 2)[key]
        runs = self._runs(item[both], group[key], pos[both], own[both], doc[both])
        if not len(runs[0]):
            return []
        item, diagonal, lo, hi, doc = runs
        pair = doc * len(self.ids) + item
        # one start for each pair first, from the middle of its runs, then all starts of the pairs that it did not settle
        order = np.lexsort((diagonal, pair))
        edges = np.append(np.flatnonzero(np.append(True, np.diff(pair[order]) > 0)), len(order))
        some = order[(edges[:-1] + edges[1:]) // 2]
        ok = self._verified(item[some], diagonal[some], (lo[some] + hi[some]) // 2, doc[some], joined, start, lengths)
        found = set(pair[some][ok].tolist())
        left = np.flatnonzero(~np.isin(pair, np.fromiter(found, np.int64, len(found))))
        for at in range(0, len(left), SIDE_BY_SIDE):
            part = left[at : at + SIDE_BY_SIDE]
            part = part[~np.isin(pair[part], np.fromiter(found, np.int64, len(found)))]
            n = hi[part] - lo[part] + 1
            each = np.repeat(part, n)
            low = np.repeat(lo[part] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
            tries = np.unique(np.stack([pair[each], item[each], diagonal[each], low, doc[each]], axis=1), axis=0)
            ok = self._verified(tries[:, 1], tries[:, 2], tries[:, 3], tries[:, 4], joined, start, lengths)
            found.update(tries[ok, 0].tolist())
        return sorted((p // len(self.ids), p % len(self.ids)) for p in found)

    def _runs(self, item: np.ndarray, group: np.ndarray, pos: np.ndarray, own: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, ...]:
        """(item, diagonal, first start, last start, doc) of runs of one band that reach the count within a passage's reach; starts are places in the item."""
        out = []
        for least in np.unique(self.least[item]) if len(item) else ():
            t = int(least)
            if len(pos) < t:
                continue
            near = np.arange(len(pos) - t + 1)
            far = near + t - 1
            near = near[(group[far] == group[near]) & (doc[far] == doc[near]) & (pos[far] - pos[near] <= SEGMENT + self.band) & (self.least[item[far]] == t)]
            window = np.lib.stride_tricks.sliding_window_view(own, t)[near]
            size = self.sizes[item[near]]
            lo = np.maximum(0, window.max(axis=1) - np.minimum(SEGMENT, size) + Q)
            hi = np.minimum(window.min(axis=1), size - np.minimum(SEGMENT, size))
            ok = lo <= hi
            out.append((item[near][ok], (pos - own)[near][ok], lo[ok], hi[ok], doc[near][ok]))
        if not out:
            return tuple(np.zeros(0, np.int64) for _ in range(5))
        runs = np.unique(np.stack([np.concatenate(x) for x in zip(*out, strict=True)], axis=1), axis=0)
        return tuple(runs.T)

    def _verified(self, item: np.ndarray, diagonal: np.ndarray, low: np.ndarray, doc: np.ndarray, joined: bytes, start: np.ndarray, lengths: np.ndarray) -> np.ndarray:
        """Whether the passage of the item that starts at low occurs, within its edits, around the diagonal (a place in joined less one in the item)."""
        out = np.zeros(len(item), bool)
        raw = np.frombuffer(joined, np.uint8)
        for at in range(0, len(item), SIDE_BY_SIDE):
            s = slice(at, at + SIDE_BY_SIDE)
            m = np.minimum(SEGMENT, self.sizes[item[s]])
            k = self.edits[item[s]]
            slack = k + 2 * self.band
            begin = np.maximum(start[doc[s]], diagonal[s] + low[s] - slack)
            end = np.minimum(start[doc[s]] + lengths[doc[s]], diagonal[s] + low[s] + m + slack)
            reach = np.maximum(0, end - begin)
            wide = np.arange(int(reach.max(initial=0)))
            region = raw[np.minimum(begin[:, None] + wide[None, :], len(raw) - 1)]
            place = np.minimum(self.begins[item[s]][:, None] + low[s][:, None] + np.arange(SEGMENT)[None, :], len(self.raw) - 1)
            out[s] = within(self.raw[place], m, region, reach, k)
        return out


def leaks(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, item_id of each document and item that share a passage."""
    items = pick(benchmark, "item_id", "text").where("item_id is not null and text is not null").selectExpr("cast(item_id as long) item_id", "cast(text as string) text")
    out = None
    for part in _parts(items):
        shared = docs.sparkSession.sparkContext.broadcast(Index(part))  # MAX_INDEX_BYTES of text at most

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            index = shared.value
            ids: list[int | None] = []
            texts: list[bytes] = []

            def found() -> pa.RecordBatch:
                got = index.search(texts)
                out = pa.RecordBatch.from_arrays([pa.array([ids[d] for d, _ in got], pa.int64()), pa.array([int(index.ids[i]) for _, i in got], pa.int64())], names=["doc_id", "item_id"])
                ids.clear()
                texts.clear()
                return out

            held = 0
            for b in batches:
                for doc, text in zip(b.column(0).to_pylist(), b.column(1).cast(pa.binary()), strict=True):
                    t = fold(text.as_py() or b"")
                    if len(t) >= Q:
                        ids.append(doc)
                        texts.append(t)
                        held += len(t)
                    if held >= CHUNK:
                        yield found()
                        held = 0
            if texts:
                yield found()

        rows = pick(docs, "doc_id", "text").selectExpr("cast(doc_id as long) doc_id", "cast(text as string) text").mapInArrow(run, "doc_id long, item_id long")
        out = rows if out is None else out.unionByName(rows)
    return out if out is not None else docs.sparkSession.createDataFrame([], "doc_id long, item_id long")


def _parts(items: DataFrame) -> Iterator[list[tuple[int, bytes]]]:
    """Items in parts whose texts have at most MAX_INDEX_BYTES, one part on the driver at a time."""
    size = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n = int(size // MAX_INDEX_BYTES) + 1
    for k in range(n):
        rows = items.where(F.pmod(F.xxhash64("item_id"), F.lit(n)) == k).toArrow() if n > 1 else items.toArrow()
        part = sorted((i, t) for i, x in zip(rows["item_id"].to_pylist(), rows["text"].to_pylist(), strict=True) if len(t := fold(x.encode())) >= MIN_ITEM)
        if part:
            yield part


def op2_decontamination(spark, sf_dir) -> DataFrame:
    return leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
