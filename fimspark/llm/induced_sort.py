"""Suffix arrays by induced sorting, with whole buckets at a time in place of one suffix after another.

Suffixes are classified as smaller (S) or larger (L) than their successor. Leftmost-S substrings are sorted by one induction, named, and the
string of their names is sorted by doubling inside the groups that are still equal; a second induction from their order gives all suffixes.
In an induction a bucket's own entries are final once all smaller (L) or larger (S) buckets are done; entries that a bucket induces
in itself follow in rounds, one for each place in a run of equal symbols; those it induces elsewhere are dealt by a stable radix sort.
"""

from __future__ import annotations

import numpy as np


def classify(t: np.ndarray) -> np.ndarray:
    """True for S; the last symbol must be the smallest and occur once."""
    n = len(t)
    ends = np.append(np.flatnonzero(t[1:] != t[:-1]), n - 1)
    kind = np.append(t[ends[:-1]] < t[ends[:-1] + 1], True)
    return np.repeat(kind, np.diff(np.append(-1, ends)))


def _deal(p: np.ndarray, symbol: np.ndarray, to: list[list[np.ndarray]]) -> None:
    order = np.argsort(symbol, kind="stable")
    p, symbol = p[order], symbol[order]
    cuts = np.flatnonzero(symbol[1:] != symbol[:-1]) + 1
    starts = np.append(0, cuts)
    for a, b, c in zip(starts.tolist(), np.append(cuts, len(p)).tolist(), symbol[starts].tolist(), strict=True):
        to[c].append(p[a:b])


def induce(t: np.ndarray, seeds: list[np.ndarray | None], size: int) -> np.ndarray:
    """All suffixes from the leftmost-S ones, given for each symbol in order."""
    none = np.zeros(0, np.int32)
    larger: list[list[np.ndarray]] = [[] for _ in range(size)]
    whole_l: list[np.ndarray] = [none] * size

    def chain(parts: list[np.ndarray], c: int) -> np.ndarray:
        at = np.concatenate(parts) if parts else none
        out = [at]
        while len(at):
            at = at[at > 0] - np.int32(1)
            at = at[t[at] == c]
            out.append(at)
        return np.concatenate(out)

    for c in range(size):
        own = whole_l[c] = chain(larger[c], c)
        source = own if seeds[c] is None else np.concatenate([own, seeds[c]])
        if len(source):
            p = source[source > 0] - np.int32(1)
            s = t[p]
            ok = s > c
            if ok.any():
                _deal(p[ok], s[ok], larger)
        larger[c] = []
    smaller: list[list[np.ndarray]] = [[] for _ in range(size)]
    smaller[int(t[-1])].append(np.asarray([len(t) - 1], np.int32))
    out: list[np.ndarray] = []
    for c in range(size - 1, -1, -1):
        own = chain(smaller[c], c)  # from the right end of the bucket
        source = np.concatenate([own, whole_l[c][::-1]])
        if len(source):
            p = source[source > 0] - np.int32(1)
            s = t[p]
            ok = s < c
            if ok.any():
                _deal(p[ok], s[ok], smaller)
            out.append(source)
        smaller[c] = []
    return np.concatenate(out)[::-1]


def _by_symbol(t: np.ndarray, rows: np.ndarray, size: int) -> list[np.ndarray | None]:
    out: list[list[np.ndarray]] = [[] for _ in range(size)]
    _deal(rows, t[rows], out)
    return [x[0] if x else None for x in out]


def _names(t: np.ndarray, order: np.ndarray, length: np.ndarray) -> np.ndarray:
    """For sorted leftmost-S substrings: whether each differs from the one before."""
    a, b = order[:-1].astype(np.int64), order[1:].astype(np.int64)
    la, lb = length[:-1], length[1:]
    new = np.append(True, la != lb)
    live = np.flatnonzero(la == lb)
    k = 0
    while len(live):
        differ = t[a[live] + k] != t[b[live] + k]
        new[live[differ] + 1] = True
        k += 1
        live = live[~differ & (la[live] > k)]
    return new


def suffix_array(t: np.ndarray, depth: int | None = None) -> np.ndarray:
    """t: uint16 symbols, the last one 0 and the only 0. depth: suffixes that agree in so many symbols may stay in any order."""
    size = int(t.max()) + 1
    if len(t) == 1:
        return np.zeros(1, np.int32)
    s = classify(t)
    lms = (np.flatnonzero(s[1:] & ~s[:-1]) + 1).astype(np.int32)
    is_lms = np.zeros(len(t), bool)
    is_lms[lms] = True
    rough = induce(t, _by_symbol(t, lms, size), size)
    order = rough[is_lms[rough]]
    index = np.zeros(len(t), np.int32)
    index[lms] = np.arange(len(lms), dtype=np.int32)
    own = index[order].astype(np.int64)
    length = np.append(np.diff(lms.astype(np.int64)), 0) + 1
    new = _names(t, order, length[own])
    m = len(lms)
    rank = np.zeros(m, np.int64)
    first = np.maximum.accumulate(np.where(new, np.arange(m), 0))
    rank[own] = first
    shared = np.append(~new[1:], False) | ~new
    live = own[shared]  # in sorted order, groups together
    k = 1
    reach = np.append(lms.astype(np.int64), np.full(1, len(t)))
    while len(live):
        if depth is not None:  # a group whose members agree that far needs no order
            live = live[reach[np.minimum(live + k, m)] - reach[live] < depth]
        if not len(live):
            break
        ahead = np.where(live + k < m, rank[np.minimum(live + k, m - 1)], -1)
        key = np.argsort(rank[live] * (m + 1) + ahead + 1, kind="stable")
        live, ahead = live[key], ahead[key]
        old = rank[live]
        start = np.append(True, old[1:] != old[:-1])
        split = start | np.append(True, ahead[1:] != ahead[:-1])
        at = np.arange(len(live))
        base = np.maximum.accumulate(np.where(start, at, 0))
        rank[live] = old + np.maximum.accumulate(np.where(split, at, 0)) - base
        live = live[~split | np.append(~split[1:], False)]
        k *= 2
    return induce(t, _by_symbol(t, lms[np.argsort(rank, kind="stable")], size), size)


def permuted_common_prefixes(raw: np.ndarray, order: np.ndarray, valid: np.ndarray, most: int) -> np.ndarray:
    """By text position: bytes that a suffix shares with the one before it in order, at most `most` (a multiple of 8 or more than 8).

    Only positions that are valid, as their predecessor is, are compared; the others have 0. Eight bytes are compared at once.
    """
    words = np.lib.stride_tricks.sliding_window_view(np.append(raw, np.zeros(most + 8, np.uint8)), 8)
    out = np.zeros(len(raw), np.int16)
    pair = np.flatnonzero(valid[order[1:]] & valid[order[:-1]])
    a, b = order[:-1][pair].astype(np.int64), order[1:][pair].astype(np.int64)
    at = 0
    while len(a):
        at_most = min(at, most - 8)
        x = words[a + at_most].copy().view(np.uint64).ravel() ^ words[b + at_most].copy().view(np.uint64).ravel()
        differ = x != 0
        low = x[differ]
        out[b[differ]] = at_most + np.bitwise_count((low & (~low + np.uint64(1))) - np.uint64(1)) // 8
        a, b = a[~differ], b[~differ]
        if at_most == most - 8:
            out[b] = most
            break
        at += 8
    return out
