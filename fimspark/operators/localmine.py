"""Mining of one projected database inside a task: a prefix tree of nodes, and growth over it.

A tree is four arrays with a place for each node: its item, its parent, its count, and the links, in which the nodes of each item stand
together. Nodes are made a depth at a time for all rows at once, and making stops as soon as the tree would pass its capacity. Trees of the recursion take
their arrays from one block made in advance, one after another, and are dropped as a whole by moving the block's end back. One that finds no
room is not made: its sets are found over the nodes of the tree above it, with more climbing and no new nodes. So a task holds its capacity and the block, and never more.

Plain growth climbs twice from an item's nodes: once to count the partners and once to make the tree. Boosted growth fills the pair counts of a
tree's items while the tree is made, so partners are known and it climbs once; a group's own anchors take theirs from the pair counts of the whole database, if these came with it.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np

from ..plans.budget import Guard

#: Items up to which a tree has pair counts; with more, partners are counted by climbing. Cells of a slice of rows when they are filled.
PAIRED_ITEMS, SLICE = 3000, 1_000_000


@dataclass
class Counters:
    """Climbs from all nodes of an item (or passes over a database in its place), trees made, nodes of the largest tree, most nodes held at once."""

    traversals: int = 0
    trees: int = 0
    nodes: int = 0
    held: int = 0


class Rows:
    """Weighted rows of rising ranks as flat arrays."""

    def __init__(self, offsets: np.ndarray, items: np.ndarray, weights: np.ndarray):
        self.offsets, self.items, self.weights = offsets, items, weights

    @classmethod
    def of(cls, lists: list[list[int]], weights: list[int] | None = None) -> Rows:
        sizes = np.asarray([len(x) for x in lists], np.int64)
        flat = np.asarray([i for x in lists for i in x], np.int64)
        return cls(np.append(0, np.cumsum(sizes)), flat, np.ones(len(lists), np.int64) if weights is None else np.asarray(weights, np.int64))

    @classmethod
    def joined(cls, parts: list[Rows]) -> Rows:
        if len(parts) == 1:
            return parts[0]
        sizes = [np.diff(p.offsets) for p in parts]
        return cls(np.append(0, np.cumsum(np.concatenate([np.zeros(0, np.int64), *sizes]))), np.concatenate([np.zeros(0, np.int64), *(p.items for p in parts)]), np.concatenate([np.zeros(0, np.int64), *(p.weights for p in parts)]))

    def __len__(self) -> int:
        return len(self.weights)

    def without_last(self) -> Rows:
        """Rows cut before their last item."""
        keep = np.ones(len(self.items), bool)
        keep[self.offsets[1:][np.diff(self.offsets) > 0] - 1] = False
        sizes = np.maximum(np.diff(self.offsets) - 1, 0)
        return Rows(np.append(0, np.cumsum(sizes)), self.items[keep], self.weights)

    def owner(self) -> np.ndarray:
        return np.repeat(np.arange(len(self)), np.diff(self.offsets))

    def only(self, place: np.ndarray) -> Rows:
        """Rows with each item replaced by its place, items without one (-1) left out."""
        at = place[self.items]
        ok = at >= 0
        sizes = np.bincount(self.owner()[ok], minlength=len(self))
        return Rows(np.append(0, np.cumsum(sizes)), at[ok], self.weights)

    def collapsed(self) -> Rows:
        """Equal rows as one; empty rows go."""
        size = np.diff(self.offsets)
        if not len(self.items):
            return Rows(np.zeros(1, np.int64), self.items, np.zeros(0, np.int64))
        ends = _grow(self, int(self.items.max()) + 1, None, None)[3]
        of, first, which = np.unique(ends, return_index=True, return_inverse=True)
        weights = np.bincount(which, self.weights, minlength=len(of)).astype(np.int64)
        first, weights = first[of >= 0], weights[of >= 0]
        n = size[first]
        at = np.repeat(self.offsets[first] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
        return Rows(np.append(0, np.cumsum(n)), self.items[at], weights)


def _grow(rows: Rows, k: int, capacity: int | None, room: int | None) -> tuple[list, int, np.ndarray | None, np.ndarray] | None:
    """Nodes of the rows' tree, a depth at a time: (item, parent, count, first row) for each depth, how many, and each row's last node (-1: empty).

    Over the capacity this raises; without room it returns None.
    """
    sizes = np.diff(rows.offsets)
    live = np.flatnonzero(sizes > 0)
    node = np.full(len(live), -1, np.int64)
    ends = np.full(len(rows), -1, np.int64)
    parts, total, depth = [], 0, 0
    guard = None if capacity is None else Guard(capacity, 0.0)
    while len(live):
        key = (node + 1) * k + rows.items[rows.offsets[live] + depth]
        order = np.argsort(key)
        key = key[order]
        new = np.append(True, key[1:] != key[:-1])
        start = np.flatnonzero(new)
        made = key[start]
        which = np.empty(len(live), np.int64)
        which[order] = np.cumsum(new) - 1
        if guard is not None:
            guard.take(len(made))
        if room is not None and total + len(made) > room:
            return None
        parts.append((made % k, made // k - 1, np.add.reduceat(rows.weights[live][order], start), live[np.minimum.reduceat(order, start)]))
        node = total + which
        total += len(made)
        depth += 1
        ends[live] = node
        more = sizes[live] > depth
        live, node = live[more], node[more]
    return parts, total, None, ends


def node_count(rows: Rows) -> int:
    """Nodes of the prefix tree of the rows: distinct prefixes."""
    return _grow(rows, int(rows.items.max(initial=0)) + 1, None, None)[1]


class Arena:
    """Places for the nodes of the recursion's trees. Without a size each tree has arrays of its own."""

    def __init__(self, size: int | None = None):
        self.size, self.used, self.most = size, 0, 0
        if size is not None:
            self.item, self.parent, self.count = np.empty(size, np.int32), np.empty(size, np.int32), np.empty(size, np.int64)

    @property
    def room(self) -> int | None:
        return None if self.size is None else self.size - self.used

    def take(self, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        at, self.used = self.used, self.used + n
        self.most = max(self.most, self.used)
        if self.size is None:
            return np.empty(n, np.int32), np.empty(n, np.int32), np.empty(n, np.int64)
        return self.item[at : at + n], self.parent[at : at + n], self.count[at : at + n]

    def back_to(self, used: int) -> None:
        self.used = used


class Tree:
    """Nodes over items (ranks, rising); pairs: counts of two items, if asked for."""

    def __init__(self, x: np.ndarray, w: np.ndarray, items: np.ndarray, pairs: bool):
        """Of 0/1 rows with a column for each item."""
        r, c = np.nonzero(x)
        sizes = np.bincount(r, minlength=len(x))
        self._fill(Rows(np.append(0, np.cumsum(sizes)), c.astype(np.int64), np.asarray(w, np.int64)), items, pairs, None, Arena())

    @classmethod
    def of(cls, rows: Rows, items: np.ndarray, pairs: bool, capacity: int | None = None, arena: Arena | None = None) -> Tree | None:
        """Of rows of places in items. None if the arena has no room."""
        tree = cls.__new__(cls)
        return tree if tree._fill(rows, items, pairs, capacity, arena or Arena()) else None

    def _fill(self, rows: Rows, items: np.ndarray, pairs: bool, capacity: int | None, arena: Arena) -> bool:
        k = max(1, len(items))
        made = _grow(rows, k, capacity, arena.room)
        if made is None:
            return False
        parts, n, _, _ = made
        self.items = items
        self.item, self.parent, self.count = arena.take(n)
        at = 0
        for item, parent, count, _ in parts:
            s = slice(at, at + len(item))
            self.item[s], self.parent[s], self.count[s] = item, parent, count
            at += len(item)
        self.links = np.argsort(self.item, kind="stable").astype(np.int32)
        self.starts = np.searchsorted(self.item[self.links], np.arange(k + 1))
        self.pairs = pair_counts(rows, k) if pairs and k <= PAIRED_ITEMS else None
        return True

    def nodes(self) -> int:
        return len(self.item)

    def of_item(self, j: int) -> np.ndarray:
        """The nodes of an item."""
        return self.links[self.starts[j] : self.starts[j + 1]]

    def support(self, j: int) -> int:
        return int(self.count[self.of_item(j)].sum())

    def partners(self, nodes: np.ndarray, weights: np.ndarray) -> np.ndarray:
        """Counts of the items above the nodes: one climb."""
        out = np.zeros(len(self.items), np.int64)
        at, w = self.parent[nodes], weights
        while True:
            ok = at >= 0
            at, w = at[ok], w[ok]
            if not len(at):
                return out
            out += np.bincount(self.item[at], w, minlength=len(out)).astype(np.int64)
            at = self.parent[at]

    def above(self, nodes: np.ndarray, weights: np.ndarray, keep: np.ndarray) -> Rows:
        """The paths above the nodes, cut to the items of keep and named by their places in it: one climb."""
        place = np.full(len(self.items), -1, np.int64)
        place[keep] = np.arange(len(keep))
        at, row, rows, found = self.parent[nodes], np.arange(len(nodes)), [], []
        while True:
            ok = at >= 0
            at, row = at[ok], row[ok]
            if not len(at):
                break
            p = place[self.item[at]]
            hit = p >= 0
            rows.append(row[hit])
            found.append(p[hit])
            at = self.parent[at]
        row = np.concatenate([np.zeros(0, np.int64), *rows[::-1]])  # from the root down
        item = np.concatenate([np.zeros(0, np.int64), *found[::-1]])
        sizes = np.bincount(row, minlength=len(nodes))
        return Rows(np.append(0, np.cumsum(sizes)), item[np.argsort(row, kind="stable")], weights)

    def up_to(self, nodes: np.ndarray, weights: np.ndarray, x: int) -> tuple[np.ndarray, np.ndarray]:
        """The nodes of item x above the nodes, with the weights that pass through them: one climb."""
        at, w, found, weight = self.parent[nodes], weights, [], []
        while len(at):
            ok = at >= 0
            at, w = at[ok], w[ok]
            hit = self.item[at] == x
            found.append(at[hit])
            weight.append(w[hit])
            go = self.item[at] > x
            at, w = self.parent[at[go]], w[go]
        kinds, which = np.unique(np.concatenate([np.zeros(0, np.int32), *found]), return_inverse=True)
        return kinds, np.bincount(which, np.concatenate([np.zeros(0, np.int64), *weight]), minlength=len(kinds)).astype(np.int64)


def pair_counts(rows: Rows, k: int) -> np.ndarray:
    """Counts of any two of k items, from some rows at a time."""
    out = np.zeros((k, k))
    step = max(1, SLICE // k)
    for lo in range(0, len(rows), step):
        hi = min(len(rows), lo + step)
        a, b = rows.offsets[lo], rows.offsets[hi]
        x = np.zeros((hi - lo, k))
        x[np.repeat(np.arange(hi - lo), np.diff(rows.offsets[lo : hi + 1])), rows.items[a:b]] = 1
        out += (x * rows.weights[lo:hi, None]).T @ x
    return np.rint(out).astype(np.int64)


@dataclass
class Search:
    """What all steps of one search share."""

    min_count: int
    max_len: int | None
    use_array: bool
    stats: Counters
    arena: Arena

    def goes_on(self, path: tuple[int, ...]) -> bool:
        return self.max_len is None or len(path) + 2 <= self.max_len


def growth(tree: Tree, path: tuple[int, ...], s: Search) -> Iterator[tuple[tuple[int, ...], int]]:
    """Frequent sets that add two items of the tree or more to the path. The items are frequent with the path."""
    if not s.goes_on(path):
        return
    for j in range(len(tree.items) - 1, 0, -1):
        nodes = tree.of_item(j)
        if s.use_array and tree.pairs is not None:
            count = tree.pairs[j, :j]
        else:
            s.stats.traversals += 1  # to count the partners
            count = tree.partners(nodes, tree.count[nodes])[:j]
        yield from _below(tree, nodes, tree.count[nodes], np.flatnonzero(count >= s.min_count), count, (*path, int(tree.items[j])), s)


def _below(tree: Tree, nodes: np.ndarray, weights: np.ndarray, partner: np.ndarray, count: np.ndarray, path: tuple[int, ...], s: Search) -> Iterator[tuple[tuple[int, ...], int]]:
    """The path's last item is at the nodes: its pairs, then the sets of the tree above the nodes."""
    for k in partner.tolist():
        yield (*path, int(tree.items[k])), int(count[k])
    if len(partner) < 2 or not s.goes_on(path):
        return
    s.stats.traversals += 1  # to make the tree
    used = s.arena.used
    sub = Tree.of(tree.above(nodes, weights, partner), tree.items[partner], s.use_array, arena=s.arena)
    if sub is None:
        yield from _in_place(tree, nodes, weights, partner, path, s)
        return
    s.stats.trees += 1
    yield from growth(sub, path, s)
    s.arena.back_to(used)


def _in_place(tree: Tree, nodes: np.ndarray, weights: np.ndarray, partner: np.ndarray, path: tuple[int, ...], s: Search) -> Iterator[tuple[tuple[int, ...], int]]:
    """As growth over the tree above the nodes, without making it."""
    for x in partner[:0:-1].tolist():
        s.stats.traversals += 2  # to the item's nodes, and from them
        at, w = tree.up_to(nodes, weights, x)
        count = tree.partners(at, w)
        below = partner[partner < x]
        below = below[count[below] >= s.min_count]
        q = (*path, int(tree.items[x]))
        for y in below.tolist():
            yield (*q, int(tree.items[y])), int(count[y])
        if len(below) >= 2 and s.goes_on(q):
            yield from _in_place(tree, at, w, below, q, s)


Partners = dict[int, tuple[np.ndarray, np.ndarray]]


def mine_group(
    rows: Rows,
    anchors: list[int],
    min_count: int,
    path: tuple[int, ...] = (),
    *,
    max_len: int | None = None,
    use_array: bool = True,
    shared_tree: bool = True,
    stats: Counters | None = None,
    partners: Partners | None = None,
    capacity: int | None = None,
) -> Iterator[tuple[tuple[int, ...], int]]:
    """Frequent sets with an anchor as their largest rank, each joined to the path.

    shared_tree: the anchors' trees come from one tree of the group; else all of them are filled in one pass over the rows. One anchor is left out of its
    own tree, whose rows all have it. partners: frequent partners (rising) of the anchors and the counts, from the pair counts of the whole database. Over
    the capacity BudgetExceeded is raised before anything is answered.
    """
    stats = Counters() if stats is None else stats
    s = Search(min_count, max_len, use_array, stats, Arena(None if capacity is None else max(1, capacity // 9)))
    known = partners or {}
    if len(anchors) == 1 or not shared_tree:
        trees = _apart(rows, sorted(anchors), s, known, capacity)
        stats.nodes = max(stats.nodes, sum(t.nodes() for *_, t in trees if t is not None))
        stats.held = max(stats.held, stats.nodes)
        for a, support, kinds, count, tree in trees:
            head = (*path, a)
            yield head, support
            if max_len is not None and len(head) >= max_len:
                continue
            for item, n in zip(kinds.tolist(), count.tolist(), strict=True):
                yield (*head, item), n
            if tree is not None and s.goes_on(head):
                yield from growth(tree, head, s)
        stats.held = max(stats.held, stats.nodes + s.arena.most)
        return
    kinds = np.unique(rows.items)
    place = np.full(int(kinds[-1]) + 1 if len(kinds) else 1, -1, np.int64)
    place[kinds] = np.arange(len(kinds))
    tree = Tree.of(rows.only(place), kinds, use_array and not known, capacity)
    stats.trees += 1
    stats.nodes = max(stats.nodes, tree.nodes())
    stats.held = max(stats.held, tree.nodes())
    for a in anchors:
        j = int(np.searchsorted(kinds, a))
        if j == len(kinds) or kinds[j] != a or tree.support(j) < min_count:
            continue
        head = (*path, a)
        yield head, tree.support(j)
        if max_len is not None and len(head) >= max_len:
            continue
        nodes = tree.of_item(j)
        count = np.zeros(len(kinds), np.int64)
        if a in known:
            items, n = known[a]
            count[np.searchsorted(kinds, items)] = n
        elif tree.pairs is not None:
            count[:j] = tree.pairs[j, :j]
        else:
            stats.traversals += 1  # to count the partners
            count = tree.partners(nodes, tree.count[nodes])
        yield from _below(tree, nodes, tree.count[nodes], np.flatnonzero(count[:j] >= min_count), count, head, s)
    stats.held = max(stats.held, tree.nodes() + s.arena.most)


def _apart(rows: Rows, anchors: list[int], s: Search, known: Partners, capacity: int | None) -> list[tuple[int, int, np.ndarray, np.ndarray, Tree | None]]:
    """(anchor, support, partners, their counts, tree without the anchor) of frequent anchors, from one pass over the rows, or two if partners are to be counted."""
    owner = rows.owner()
    hit = np.flatnonzero(np.isin(rows.items, anchors))
    order = np.argsort(rows.items[hit], kind="stable")
    hit = hit[order]
    cuts = np.searchsorted(rows.items[hit], anchors)
    ends = np.searchsorted(rows.items[hit], anchors, side="right")
    out, left = [], capacity
    for a, lo, hi in zip(anchors, cuts.tolist(), ends.tolist(), strict=True):
        at = hit[lo:hi]
        own = owner[at]
        weights = rows.weights[own]
        support = int(weights.sum())
        if support < s.min_count:
            continue
        start, length = rows.offsets[own], at - rows.offsets[own]
        flat = np.repeat(start - (np.cumsum(length) - length), length) + np.arange(int(length.sum()))
        mine = Rows(np.append(0, np.cumsum(length)), rows.items[flat], weights)
        if a in known:
            kinds, count = known[a]
        else:
            s.stats.traversals += 1  # to count the partners
            kinds, which = np.unique(mine.items, return_inverse=True)
            count = np.bincount(which, weights[mine.owner()], minlength=len(kinds)).astype(np.int64)
            kinds, count = kinds[count >= s.min_count], count[count >= s.min_count]
        tree = None
        if len(kinds) >= 2:
            place = np.full(int(max(mine.items.max(initial=0), kinds[-1])) + 1, -1, np.int64)
            place[kinds] = np.arange(len(kinds))
            s.stats.traversals += 1  # to make the tree
            s.stats.trees += 1
            tree = Tree.of(mine.only(place), kinds, s.use_array, left)
            left = None if left is None else left - tree.nodes()
        out.append((a, support, kinds, count, tree))
    return out


def mine_all(rows: Rows, min_count: int, **options) -> list[tuple[tuple[int, ...], int]]:
    """All frequent sets of a whole database in memory; ranks must be frequent ones."""
    return list(mine_group(rows, sorted(set(rows.items.tolist())), min_count, **options))
