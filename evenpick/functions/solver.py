"""The static matching-based solver on rows that fit the driver, with the exact one for tests.

Greedy pivots; the longest prefix whose pivots can be matched to groups inside half the gap at which the prefix's last pivot was
added (such balls are disjoint, so matched members differ); then the least radius that still saturates.
"""

from __future__ import annotations

from collections.abc import Mapping
from dataclasses import dataclass
from itertools import combinations, product

import numpy as np

from evenpick.functions.kernels import farthest_first, min_dist_block
from evenpick.functions.matching import match_pivots, saturates
from evenpick.functions.metrics import Metric, metric


@dataclass
class Solution:
    """Rows chosen as centers (indices), and what the solver found on the way."""

    rows: list[int]
    prefix: int = 0
    radius: float = 0.0
    greedy_radius: float = 0.0


def check_caps(caps: Mapping[int, int]) -> dict[int, int]:
    caps = {int(g): int(c) for g, c in caps.items()}
    if any(c < 0 for c in caps.values()) or not sum(caps.values()):
        raise ValueError("capacities must be non-negative and not all zero")
    return caps


def nearest_members(x, grp, pivots, groups, m: Metric) -> tuple[np.ndarray, np.ndarray]:
    """(distance, row) of the nearest member of each group for each pivot; inf where a group is empty."""
    dist, row = np.full((len(pivots), len(groups)), np.inf), np.full((len(pivots), len(groups)), -1)
    members = [np.flatnonzero(grp == g) for g in groups]
    for i, p in enumerate(pivots):
        d = m.one_to_many(x[p], x)
        for j, rows in enumerate(members):
            if len(rows):
                at = int(d[rows].argmin())
                dist[i, j], row[i, j] = d[rows[at]], rows[at]
    return dist, row


def solve_static(x: np.ndarray, grp: np.ndarray, caps: Mapping[int, int], m: Metric | str = "l1", fill: str = "none") -> Solution:
    """3-approximation. ``fill='greedy'`` spends spare capacity on the farthest rows of groups with room."""
    m, caps = metric(m), check_caps(caps)
    if not len(x):
        raise ValueError("no rows to choose from")
    pivots, delta, greedy, _, _ = farthest_first(x, sum(caps.values()), m)
    groups = sorted(g for g, c in caps.items() if c > 0)
    dist, row = nearest_members(x, grp, pivots, groups, m)

    def lists(h: int, ok) -> list[list[int]]:
        return [[g for j, g in enumerate(groups) if ok(dist[i, j])] for i in range(h)]

    def passes(h: int) -> bool:
        return saturates(lists(h, lambda d: d < delta[h - 1] / 2), caps)

    if not passes(1):
        raise ValueError("no row belongs to a group with capacity")
    low, high = 1, len(pivots)
    while low < high:
        mid = (low + high + 1) // 2
        low, high = (mid, high) if passes(mid) else (low, mid - 1)
    h = low
    radii = np.unique(dist[:h][dist[:h] < delta[h - 1] / 2])
    a, b = 0, len(radii) - 1
    while a < b:
        mid = (a + b) // 2
        a, b = (a, mid) if saturates(lists(h, lambda d: d <= radii[mid]), caps) else (mid + 1, b)
    rho = float(radii[a])
    chosen = match_pivots(lists(h, lambda d: d <= rho), caps)
    rows = [int(row[i, groups.index(g)]) for i, g in enumerate(chosen)]
    if fill == "greedy":
        rows += fill_greedy(x, grp, caps, rows, m)
    return Solution(rows, h, rho, greedy)


def fill_greedy(x, grp, caps, rows: list[int], m: Metric) -> list[int]:
    left = {g: c - sum(1 for r in rows if grp[r] == g) for g, c in caps.items()}
    dist, _ = min_dist_block(x, x[rows], m)
    more: list[int] = []
    while any(c > 0 for c in left.values()):
        open_ = np.isin(grp, [g for g, c in left.items() if c > 0]) & (dist > 0)
        if not open_.any():
            break
        at = int(np.where(open_, dist, -1).argmax())
        more.append(at)
        left[int(grp[at])] -= 1
        dist = np.minimum(dist, m.one_to_many(x[at], x))
    return more


def solve_exact(x: np.ndarray, grp: np.ndarray, caps: Mapping[int, int], m: Metric | str = "l1", limit: int = 2_000_000) -> Solution:
    """Optimum by trying every maximal feasible choice (small inputs only)."""
    m, caps = metric(m), check_caps(caps)
    d = m.block(x, x)
    choices, size = [], 1
    for g, c in sorted(caps.items()):
        rows = np.flatnonzero(grp == g)
        picks = list(combinations(rows.tolist(), min(c, len(rows))))
        size *= len(picks)
        if size > limit:
            raise ValueError("too many feasible choices for the exact solver")
        choices.append(picks)
    best, pick = np.inf, ()
    for combo in product(*choices):
        rows = sum(combo, ())
        if rows and (cost := d[:, list(rows)].min(1).max()) < best:
            best, pick = cost, rows
    return Solution(sorted(pick), len(pick), float(best), float("nan"))


SOLVERS = {"static": solve_static, "exact": solve_exact}
