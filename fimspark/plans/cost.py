"""Analytic costs: passes, and transfers of blocks of B bytes for a database of D bytes."""

from __future__ import annotations

import math


def passes(memory: float, tree: float, shrink: float) -> int:
    """Passes of the general scheme when conditional trees shrink by a factor below 1 each time.

    With 2**30 bytes of memory and a factor of 0.1: 2 for a tree of 10 * 2**30, and 6 for 10 * 2**40 (5 in decimal units, 1e9 and 1e13).
    """
    if tree <= memory:
        return 1
    return 1 + math.ceil(math.log(memory / tree) / math.log(shrink) - 1e-9)


def io_projection(d: float, projected: float, b: float) -> float:
    """Two scans, and projected databases written once and read twice."""
    return 2 * d / b + 3 * projected / b


def io_per_item(d: float, n: float, b: float, exact: bool = False) -> float:
    """n: mean number of frequent items in a row; exact: (n + 1) / 2 in place of n / 2 copies."""
    return io_projection(d, (n + exact) / 2 * d, b)


def io_grouped(d: float, k: float, b: float, exact: bool = False) -> float:
    return io_projection(d, (k + exact) / 2 * d, b)


def io_budgeted(d: float, k: float, b: float, form: str = "printed") -> float:
    """printed: the formula as published, 3/2 + k scans; itemised: what its own terms (two scans, half a scan, k) add up to, 5/2 + k."""
    return ({"printed": 1.5, "itemised": 2.5}[form] + k) * d / b


def saving(k: float, d: float, b: float, form: str = "printed") -> float:
    """What the budgeted miner spares against equal groups."""
    return io_grouped(d, k, b) - io_budgeted(d, k, b, form)


def extrapolate(seconds: float, d: float, d_new: float, k: float, k_new: float | None = None) -> float:
    """Time at another size, in proportion to the transfers of the budgeted miner."""
    return seconds * io_budgeted(d_new, k if k_new is None else k_new, 1) / io_budgeted(d, k, 1)
