"""Budgets in prefix-tree nodes."""

from __future__ import annotations

from dataclasses import dataclass

#: Share of a tree's size that its descendants take: a tree may fill the rest.
WORKSPACE = 0.10
#: A node's item, parent, count and link, and its share of the index of links.
BYTES_PER_NODE = 24


class BudgetExceeded(Exception):
    """A structure would need more nodes than its task may hold."""


def usable_nodes(node_budget: int, workspace: float = WORKSPACE) -> int:
    return max(1, int((1 - workspace) * node_budget + 1e-9))


def nodes_for_bytes(n_bytes: int, bytes_per_node: int = BYTES_PER_NODE) -> int:
    return max(1, n_bytes // bytes_per_node)


@dataclass
class Guard:
    """Counts nodes handed out and stops before the budget is passed, instead of letting the machine page."""

    node_budget: int
    workspace: float = WORKSPACE
    used: int = 0

    def take(self, nodes: int) -> None:
        if self.used + nodes > usable_nodes(self.node_budget, self.workspace):
            raise BudgetExceeded(f"{self.used + nodes} nodes of {usable_nodes(self.node_budget, self.workspace)}")
        self.used += nodes
