"""From statistics to groups of consecutive anchors.

Sizes of trees are taken from the pilot and scaled by total rows over pilot rows: as if the rest of the rows brought as many new nodes as the pilot did.
That is usually too much, since later rows mostly meet nodes that are there.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np

from ..operators.stats import StatsBundle


@dataclass
class Group:
    lo: int
    hi: int
    est_nodes: float
    companions: list[int] | None = None  # None: all ranks before lo
    anchors: list[int] = field(default_factory=list)

    def __post_init__(self):
        self.anchors = self.anchors or [*range(self.lo, self.hi + 1)]

    @property
    def singleton(self) -> bool:
        return self.lo == self.hi


def scaled(x: float, n_used: int, n_total: int) -> float:
    return x * n_total / n_used if n_used else float("inf") * (x > 0)


def cut_ratio(s: StatsBundle, capacity: int) -> int:
    """As many of the items as the share of the rows that the pilot took."""
    return int(s.n * s.n_used // s.n_total) if s.n_total else s.n


def cut_nu(s: StatsBundle, capacity: int) -> int:
    """The last rank whose trimmed tree fits."""
    fits = np.flatnonzero(s.nu[1:] * s.scale <= capacity)
    return int(fits[-1]) + 1 if len(fits) else 0


def cut_nu_mu(s: StatsBundle, capacity: int) -> int:
    """The last rank whose trimmed tree fits together with the largest single-anchor tree that comes from it."""
    fits = np.flatnonzero((s.nu[1:] + np.maximum.accumulate(s.mu[1:])) * s.scale <= capacity)
    return int(fits[-1]) + 1 if len(fits) else 0


CUTS: dict[str, Callable[[StatsBundle, int], int]] = {"ratio": cut_ratio, "nu": cut_nu, "nu_mu": cut_nu_mu}


def fits_alone(s: StatsBundle, j: int, capacity: int) -> bool:
    return bool(s.mu[j] * s.scale <= capacity)


def pack(s: StatsBundle, start: int, capacity: int, size: Callable[[int, int], float]) -> list[Group]:
    """Consecutive groups from start on: an item joins while the estimate of the group fits; one that does not fit even alone is a group by itself."""
    out, lo = [], start
    while lo <= s.n:
        hi = lo
        while hi < s.n and size(lo, hi + 1) * s.scale <= capacity:
            hi += 1
        out.append(Group(lo, hi, size(lo, hi) * s.scale))
        lo = hi + 1
    return out


def mu_sum(s: StatsBundle) -> Callable[[int, int], float]:
    total = np.cumsum(s.mu)
    return lambda lo, hi: float(total[hi] - total[lo - 1])


def union_size(rows: list[list[int]] | tuple[np.ndarray, np.ndarray]) -> Callable[[int, int], float]:
    """Size of the joint tree of consecutive anchors on the pilot: the prefixes, up to its last anchor, of each branch that has one.

    rows: the pilot's rows, or the item and parent of its nodes, parents first. For a first anchor a node counts from the least anchor at it or below it on; these are found for all
    nodes in one walk from the leaves to the root, and give the sizes for every last anchor.
    """
    from ..operators.localmine import Rows, Tree

    if isinstance(rows, list):
        most = max((max(r) for r in rows if r), default=0)
        tree = Tree.of(Rows.of([r for r in rows if r]), np.arange(most + 1), False)
        rows = (tree.item.astype(np.int64), tree.parent.astype(np.int64))
    item, parent = rows
    most = int(item.max(initial=0))
    depth = np.zeros(len(item), np.int64)
    at = parent
    while (at >= 0).any():
        depth += at >= 0
        at = np.where(at >= 0, parent[at], -1)
    by_depth = [np.flatnonzero((depth == d)) for d in range(int(depth.max(initial=0)), 0, -1)]
    known: dict[int, np.ndarray] = {}

    def size(lo: int, hi: int) -> float:
        if lo not in known:
            known.clear()  # groups are packed one after another
            least = np.where(item >= lo, item, most + 1)
            for some in by_depth:
                np.minimum.at(least, parent[some], least[some])
            known[lo] = np.cumsum(np.bincount(least, minlength=most + 2))
        return float(known[lo][min(hi, most)])

    return size


def plan(s: StatsBundle, capacity: int, cut: str = "nu_mu", packing: str = "mu_sum", pilot_rows: list[list[int]] | tuple[np.ndarray, np.ndarray] | None = None) -> list[Group]:
    """The prefix head up to the cut point, if any, then packed groups."""
    head = min(s.n, CUTS[cut](s, capacity))
    out = [Group(1, head, float(s.nu[head]) * s.scale)] if head else []
    return out + pack(s, head + 1, capacity, union_size(pilot_rows or []) if packing == "union" else mu_sum(s))


def equal_groups(n: int, k: int) -> list[Group]:
    """k consecutive groups whose sizes differ by one at most, the larger ones first (as NTILE deals)."""
    k = max(1, min(k, n))
    out, lo = [], 1
    for g in range(k):
        size = n // k + (g < n % k)
        out.append(Group(lo, lo + size - 1, float("nan")))
        lo += size
    return out if n else []


def next_action(g: Group, capacity: int) -> str:
    """recurse: a lone anchor whose tree is thought too large; mine: everything else."""
    return "recurse" if g.singleton and g.est_nodes > capacity else "mine"
