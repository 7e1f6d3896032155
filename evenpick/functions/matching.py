"""Assigning pivots to groups within capacities: augmenting paths, and Hall's condition over group masks."""

from __future__ import annotations

from collections.abc import Mapping, Sequence


def _augment(i: int, adj: Sequence[Sequence[int]], caps: Mapping[int, int], held: dict[int, list[int]], seen: set[int]) -> bool:
    for g in adj[i]:
        if g in seen or caps.get(g, 0) <= 0:
            continue
        seen.add(g)
        mine = held.setdefault(g, [])
        if len(mine) < caps[g]:
            mine.append(i)
            return True
        for slot, other in enumerate(mine):
            if _augment(other, adj, caps, held, seen):
                mine[slot] = i
                return True
    return False


def saturates(adj: Sequence[Sequence[int]], caps: Mapping[int, int]) -> bool:
    """Whether every pivot can get a group of its list without exceeding a capacity."""
    held: dict[int, list[int]] = {}
    return all(_augment(i, adj, caps, held, set()) for i in range(len(adj)))


def match_pivots(adj: Sequence[Sequence[int]], caps: Mapping[int, int]) -> list[int] | None:
    """The lexicographically least saturating assignment (one group per pivot), or None."""
    adj = [sorted(a) for a in adj]
    if not saturates(adj, caps):
        return None
    left, chosen = dict(caps), []
    for i in range(len(adj)):
        for g in adj[i]:
            if left.get(g, 0) > 0:
                left[g] -= 1
                if saturates(adj[i + 1 :], left):
                    chosen.append(g)
                    break
                left[g] += 1
    return chosen


def hall_feasible(masks: Sequence[int], caps: Mapping[int, int]) -> bool:
    """Hall's condition: for every set of groups, no more pivots are confined to it than it may take (2^m sets)."""
    groups = sorted(caps)
    for t in range(1 << len(groups)):
        allowed = sum(1 << g for b, g in enumerate(groups) if t >> b & 1)
        if sum(1 for mask in masks if mask & ~allowed == 0) > sum(caps[g] for b, g in enumerate(groups) if t >> b & 1):
            return False
    return True
