"""Exact removal of byte strings that also start in a document of smaller doc_id, by suffix arrays of shards.

A window of MIN bytes is told by its anchor: of the GRAM-byte strings in it, the one of least hash. Successive windows with
one anchor form an entry: at most MIN - GRAM + 1 windows and their bytes. Equal windows have equal anchors, so they meet in one shard.

1. Texts are dealt to parts once, by doc_id; every step below works on a part and sends on what it has aggregated.
2. Each part sends the hashes of its anchors with how many of its texts have them; a hash goes on if two texts or more have it.
3. Each part sends, for such hashes, its distinct entries with the least doc_id of each, to the hash's shard. A hash in more than HOT
   texts would fill a shard: its windows are sent one by one instead, to the shard of their own bytes.
4. A shard merges equal entries, sorts the suffixes of the others by induction, computes permuted common prefixes, and takes the least doc_id of each run of
   suffixes that share MIN bytes. It answers each part with a bit for each window: whether that doc_id is smaller than the entry's.
5. Each part lists its entries again in the same order and removes what is covered.

Equal texts are found first: all but those of the least doc_id are covered as a whole (if they have a window at all) and do not enter the steps above.

A null text has no bytes. Texts shorter than MIN bytes keep all. Rows of one doc_id count as one document, so none of them removes from another;
rows with a null doc_id neither lose bytes nor cause losses. Repeated rows get the same result each. An empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, pick, table
from .induced_sort import permuted_common_prefixes, suffix_array

MIN, GRAM = 50, 20
WINDOWS = MIN - GRAM + 1
HOT = 100_000
#: Bytes of text in a part, anchors in a bucket of step 2, bytes of text for each shard of step 4, bytes searched at once.
PART_BYTES, BUCKET_ANCHORS, SHARD_TEXT, CHUNK = 4 << 20, 400_000, 8 << 20, 2 << 20
_ANCHORS_A_BYTE = 2 / (WINDOWS + 1)
#: What a row tells a part: a text that another document has, hashes that occur elsewhere, a shard's answer.
COPY, KNOWN, MASKS = 0, 1, 2
ALL = np.uint64((1 << 63) - 1)


def _mix(x: np.ndarray) -> np.ndarray:
    x = x * np.uint64(0x9E3779B97F4A7C15)
    x ^= x >> np.uint64(32)
    x *= np.uint64(0xD6E8FEB86659FD93)
    x ^= x >> np.uint64(29)
    return x


def entries_of(texts: list[bytes]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray, bytes]]:
    """(text, place in it, windows, hash of the anchor, place in the joined bytes, joined bytes), for some texts at a time."""
    lo = 0
    while lo < len(texts):
        hi, n = lo, 0
        while hi < len(texts) and (n < CHUNK or hi == lo):
            n += len(texts[hi])
            hi += 1
        joined = b"".join(texts[lo:hi])
        x = np.frombuffer(joined, np.uint8)
        if len(x) >= MIN:
            words = np.lib.stride_tricks.sliding_window_view(x, 8).copy().view(np.uint64).ravel()
            many = len(x) - GRAM + 1
            h = _mix(_mix(words[:many]) + words[8 : 8 + many])
            h = _mix(h + words[GRAM - 8 : GRAM - 8 + many])
            low = np.uint64((1 << max(24, many.bit_length())) - 1)
            least = (h & ~low) | np.arange(many, dtype=np.uint64)  # ties go to the leftmost
            width = 1
            while width * 2 <= WINDOWS:
                least = np.minimum(least[:-width], least[width:])
                width *= 2
            if width < WINDOWS:
                least = np.minimum(least[: len(least) - (WINDOWS - width)], least[WINDOWS - width :])
            anchor = (least & low).astype(np.int64)
            sizes = np.asarray([len(t) for t in texts[lo:hi]])
            text = np.repeat(np.arange(lo, hi), sizes)
            inside = text[: len(anchor)] == text[MIN - 1 :]
            change = (anchor[1:] != anchor[:-1]) | (text[1 : len(anchor)] != text[: len(anchor) - 1])
            first = np.flatnonzero(inside & np.append(True, change | ~inside[:-1]))
            last = np.flatnonzero(inside & np.append(change | ~inside[1:], True))
            if len(first):
                of = text[first]
                yield of, first - (np.cumsum(sizes) - sizes)[of - lo], last - first + 1, h[anchor[first]], first, joined
        lo = hi


class Part:
    """A part's texts in a fixed order, with what other steps have told it."""

    def __init__(self, t: pa.Table, marks: pa.Table, n_shards: int):
        told = [*zip(marks["kind"].to_pylist(), marks["shard"].to_pylist(), marks["data"].to_pylist(), strict=True)]
        ids, raw = t["doc_id"].to_pylist(), [x or b"" for x in t["text"].cast(pa.binary()).to_pylist()]
        order = sorted(range(len(ids)), key=lambda i: (ids[i] is None, ids[i] or 0, raw[i]))
        self.ids, self.raw = [ids[i] for i in order], [raw[i] for i in order]
        copies = {b for kind, _, b in told if kind == COPY}
        self.copy = [bool(copies) and i is not None and (i.to_bytes(8, "big", signed=True) + hashlib.sha256(x).digest()) in copies for i, x in zip(self.ids, self.raw, strict=True)]
        self.rows = [k for k, (i, x) in enumerate(zip(self.ids, self.raw, strict=True)) if i is not None and len(x) >= MIN and not self.copy[k]]
        self.texts = [self.raw[k] for k in self.rows]
        known = [np.frombuffer(b, np.uint64) for kind, _, b in told if kind == KNOWN]
        self.known = np.sort(np.concatenate(known)) if known else np.zeros(0, np.uint64)
        self.masks = {shard: np.frombuffer(b, np.uint64) for kind, shard, b in told if kind == MASKS}
        self.n_shards = n_shards

    def anchors(self) -> np.ndarray:
        """Upper 56 bits of each hash, over how many texts have it (255 at most), sorted."""
        got = []
        for text, _, _, h, _, _ in entries_of(self.texts):
            order = np.lexsort((text, h))
            h, text = h[order], text[order]
            got.append((h >> np.uint64(8))[np.append(True, (h[1:] != h[:-1]) | (text[1:] != text[:-1]))])
        if not got:
            return np.zeros(0, np.uint64)
        key, n = np.unique(np.concatenate(got), return_counts=True)
        return key << np.uint64(8) | np.minimum(n, 255).astype(np.uint64)

    def merged(self) -> tuple[dict[int, dict[bytes, int]], dict[int, list[int]], dict[int, list[int]], np.ndarray]:
        """For each shard met its distinct entries, their least doc_ids and 32 bits of their anchors; and each entry's (text, place, windows, shard, number)."""
        numbers: dict[int, dict[bytes, int]] = defaultdict(dict)
        least: dict[int, list[int]] = defaultdict(list)
        tags: dict[int, list[int]] = defaultdict(list)
        places: list[tuple[int, int, int, int, int]] = []
        keys, hot = self.known >> np.uint64(1), (self.known & np.uint64(1)).astype(bool)
        for text, place, windows, h, start, joined in entries_of(self.texts) if len(keys) else ():
            h = h >> np.uint64(8)
            k = np.minimum(np.searchsorted(keys, h), len(keys) - 1)
            ok = np.flatnonzero(keys[k] == h)
            shards = (_mix(h[ok]) % np.uint64(self.n_shards)).tolist()
            own_tags = (h[ok] & np.uint64(0xFFFFFFFF)).tolist()
            for x, p, w, a, sh, tag, each in zip(text[ok].tolist(), place[ok].tolist(), windows[ok].tolist(), start[ok].tolist(), shards, own_tags, hot[k[ok]].tolist(), strict=True):
                own = self.ids[self.rows[x]]
                for j, many in ((0, w),) if not each else [(j, 1) for j in range(w)]:
                    b = joined[a + j : a + j + many + MIN - 1]
                    if each:
                        digest = int.from_bytes(hashlib.blake2b(b, digest_size=8).digest(), "little")
                        sh, tag = digest % self.n_shards, digest >> 32
                    n = numbers[sh].setdefault(b, len(numbers[sh]))
                    if n == len(least[sh]):
                        least[sh].append(own)
                        tags[sh].append(tag)
                    elif own < least[sh][n]:
                        least[sh][n] = own
                    places.append((x, p + j, many, sh, n))
        return numbers, least, tags, np.asarray(places, np.int64).reshape(-1, 5)

    def cleaned(self) -> pa.Table:
        _, least, _, places = self.merged()
        begin = np.cumsum([0, *(len(t) for t in self.texts)])
        delta = np.zeros(begin[-1] + 1, np.int32)
        if len(places):
            x, place, many, shard, n = places.T
            met = sorted(least)
            first = np.cumsum([0, *(len(least[s]) for s in met)])[np.searchsorted(met, shard)] + n
            every = np.concatenate([np.asarray(least[s], np.int64) for s in met])
            mask = np.concatenate([self.masks.get(s, np.zeros(len(least[s]), np.uint64))[: len(least[s])] for s in met])
            own = np.asarray([self.ids[k] for k in self.rows], np.int64)[x]
            bits = np.where(own > every[first], ALL, mask[first])
            for j in range(WINDOWS):
                at = (begin[x] + place + j)[((bits >> np.uint64(j)) & np.uint64(1)).astype(bool) & (j < many)]
                np.add.at(delta, at, 1)
                np.add.at(delta, at + MIN, -1)
        gone = np.cumsum(delta[:-1]) > 0
        where = {k: j for j, k in enumerate(self.rows)}
        out = []
        for k, (i, b) in enumerate(zip(self.ids, self.raw, strict=True)):
            removed, spans, kept = 0, 0, b
            if self.copy[k]:
                removed, spans, kept = len(b), 1, b""
            elif k in where:
                g = gone[begin[where[k]] : begin[where[k] + 1]]
                removed = int(g.sum())
                if removed:
                    spans = int(g[0]) + int((g[1:] & ~g[:-1]).sum())
                    kept = np.frombuffer(b, np.uint8)[~g].tobytes()
            out.append((i, len(b), removed, spans, hashlib.sha256(kept).hexdigest(), kept))
        names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"]
        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary()]
        return pa.table({c: pa.array([r[k] for r in out], kind) for k, (c, kind) in enumerate(zip(names, kinds, strict=True))})


def _known(t: pa.Table) -> pa.Table:
    """A bucket of step 2: to each part, its hashes that two texts or more have, over a bit for hot ones."""
    parts, blobs = t["part"].to_pylist(), [np.frombuffer(b, np.uint64) for b in t["data"].to_pylist()]
    every = np.concatenate(blobs)
    order = np.argsort(every >> np.uint64(8), kind="stable")
    key, n = (every >> np.uint64(8))[order], (every & np.uint64(255)).astype(np.int64)[order]
    first = np.flatnonzero(np.append(True, key[1:] != key[:-1]))
    total = np.add.reduceat(n, first)
    key, total = key[first], total
    key, total = key[total > 1], total[total > 1]
    out = []
    for b in blobs:
        own = b >> np.uint64(8)
        k = np.minimum(np.searchsorted(key, own), max(len(key) - 1, 0))
        ok = key[k] == own if len(key) else np.zeros(len(own), bool)
        out.append((own[ok] << np.uint64(1) | (total[k[ok]] > HOT).astype(np.uint64)).tobytes())
    return pa.table({"part": pa.array(parts, pa.int64()), "kind": pa.array([KNOWN] * len(parts), pa.int32()), "shard": pa.array([0] * len(parts), pa.int32()), "data": pa.array(out, pa.binary())})


def shard_masks(strings: list[bytes], least: np.ndarray) -> np.ndarray:
    """For distinct byte strings and the least doc_id of each: a bit for each window, set if it is in a string of a smaller one."""
    sizes = np.asarray([len(s) for s in strings], np.int64)
    raw = np.frombuffer(b"\0".join(strings) + b"\0", np.uint8)
    start = np.cumsum(sizes + 1) - sizes - 1
    of = np.repeat(np.arange(len(strings)), sizes + 1)
    place = np.arange(len(raw)) - start[of]
    valid = place + MIN <= sizes[of]
    symbols = raw.astype(np.uint16) + np.uint16(2)
    symbols[start + sizes] = 1
    order = suffix_array(np.append(symbols, np.uint16(0)), depth=MIN)
    order = order[order < len(raw)]
    prefix = permuted_common_prefixes(raw, order, valid, MIN)
    at = order[valid[order]]
    owner = least[of[at]]
    first = np.flatnonzero(prefix[at] < MIN)
    smallest = np.repeat(np.minimum.reduceat(owner, first), np.diff(np.append(first, len(at))))
    lost = at[smallest < owner]
    mask = np.zeros(len(strings), np.uint64)
    np.bitwise_or.at(mask, of[lost], np.uint64(1) << place[lost].astype(np.uint64))
    return mask


def _answer(t: pa.Table) -> pa.Table:
    """A shard of step 4."""
    numbers: dict[bytes, int] = {}
    least: list[int] = []
    anchor: list[int] = []
    rows = []
    for blob, sizes, own, tags in zip(*(t[c].to_pylist() for c in ("entries", "sizes", "least", "tags")), strict=True):
        sizes, own, mine, at = np.frombuffer(sizes, np.uint16), np.frombuffer(own, np.int64), [], 0
        for size, d, tag in zip(sizes.tolist(), own.tolist(), np.frombuffer(tags, np.uint32).tolist(), strict=True):
            b = blob[at : at + size]
            at += size
            n = numbers.setdefault(b, len(numbers))
            if n == len(least):
                least.append(d)
                anchor.append(tag)
            elif d < least[n]:
                least[n] = d
            mine.append(n)
        rows.append((np.asarray(mine, np.int64), own))
    smallest = np.asarray(least, np.int64)
    # strings with an anchor of their own share no window with any other here
    _, which, many = np.unique(np.asarray(anchor, np.uint32), return_inverse=True, return_counts=True)
    some = np.flatnonzero(many[which] > 1)
    mask = np.zeros(len(smallest), np.uint64)
    if len(some):
        strings = list(numbers)
        mask[some] = shard_masks([strings[k] for k in some], smallest[some])
    out = [np.where(own > smallest[mine], ALL, mask[mine]).astype(np.uint64).tobytes() for mine, own in rows]
    return pa.table({"part": t["part"].cast(pa.int64()), "kind": pa.array([MASKS] * len(out), pa.int32()), "shard": t["shard"].cast(pa.int32()), "data": pa.array(out, pa.binary())})


def remove_repeats(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 and the kept bytes."""
    spark = docs.sparkSession
    d = pick(docs, "doc_id", "text").selectExpr("cast(doc_id as long) doc_id", "coalesce(cast(text as string), '') text")
    brief = cut(d.select("doc_id", F.unhex(F.sha2("text", 256)).alias("sha"), F.octet_length("text").cast("long").alias("n")))
    total = brief.agg(F.sum("n")).first()[0] or 0
    n_parts, n_shards = int(total // PART_BYTES) + 1, int(total // SHARD_TEXT) + 1
    n_buckets = int(total * _ANCHORS_A_BYTE // BUCKET_ANCHORS) + 1
    width = max(int(spark.conf.get("spark.sql.shuffle.partitions")), n_parts // 2)
    part = F.pmod(F.xxhash64(F.coalesce("doc_id", F.xxhash64("text"))), F.lit(n_parts).cast("long")).alias("part")
    first = brief.where(f"doc_id is not null and n >= {MIN}").groupBy("sha").agg(F.min("doc_id").alias("first"), F.count(F.lit(1)).alias("many")).where("many > 1")
    copies = brief.join(first, "sha").where("doc_id > first")
    copies = copies.select(F.pmod(F.xxhash64("doc_id"), F.lit(n_parts).cast("long")).alias("part"), F.lit(COPY).alias("kind"), F.lit(0).alias("shard"), F.concat(F.unhex(F.lpad(F.hex("doc_id"), 16, "0")), "sha").alias("data")).repartition(width, "part")
    texts = d.select("doc_id", "text", part).repartition(width, "part")
    marks = "part long, kind int, shard int, data binary"

    def anchors(t: pa.Table, m: pa.Table) -> pa.Table:
        got = Part(t, m, n_shards).anchors()
        bucket = (_mix(got >> np.uint64(8)) >> np.uint64(20)) % np.uint64(n_buckets)
        order = np.argsort(bucket, kind="stable")
        got, bucket = got[order], bucket[order]
        start = np.flatnonzero(np.append(np.ones(min(1, len(got)), bool), bucket[1:] != bucket[:-1]))
        blobs = [x.tobytes() for x in np.split(got, start[1:])] if len(got) else []
        own = t["part"][0].as_py() if t.num_rows else 0
        return pa.table({"bucket": pa.array(bucket[start].astype(np.int64)), "part": pa.array([own] * len(blobs), pa.int64()), "data": pa.array(blobs, pa.binary())})

    def entries(t: pa.Table, m: pa.Table) -> pa.Table:
        numbers, least, tags, _ = Part(t, m, n_shards).merged()
        full = sorted(numbers)
        own = t["part"][0].as_py() if t.num_rows else 0
        return pa.table(
            {
                "shard": pa.array(full, pa.int32()),
                "part": pa.array([own] * len(full), pa.int64()),
                "entries": pa.array([b"".join(numbers[s]) for s in full], pa.binary()),
                "sizes": pa.array([np.asarray([len(b) for b in numbers[s]], np.uint16).tobytes() for s in full], pa.binary()),
                "least": pa.array([np.asarray(least[s], np.int64).tobytes() for s in full], pa.binary()),
                "tags": pa.array([np.asarray(tags[s], np.uint32).tobytes() for s in full], pa.binary()),
            }
        )

    by_part = texts.groupBy("part")
    sent = by_part.cogroup(copies.groupBy("part")).applyInArrow(anchors, "bucket long, part long, data binary")
    known = sent.groupBy("bucket").applyInArrow(_known, marks).repartition(width, "part")
    to_shards = by_part.cogroup(copies.unionByName(known).groupBy("part")).applyInArrow(entries, "shard int, part long, entries binary, sizes binary, least binary, tags binary")
    masks = to_shards.groupBy("shard").applyInArrow(_answer, marks).repartition(width, "part")
    told = copies.unionByName(known).unionByName(masks)
    return by_part.cogroup(told.groupBy("part")).applyInArrow(lambda t, m: Part(t, m, n_shards).cleaned(), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary")


def op7_substring_dedup(spark, sf_dir) -> DataFrame:
    return remove_repeats(table(spark, sf_dir, "documents")).drop("kept")
