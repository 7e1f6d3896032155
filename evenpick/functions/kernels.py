"""NumPy kernels: greedy pivots, nets with group representatives, merges, and the two incremental structures.

Rows are processed in the given order; all ties go to the earlier row, so callers order rows by ``point_id``.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from evenpick.functions.metrics import Metric, metric
from evenpick.functions.packed import PackedRows

Rep = tuple[int, np.ndarray, float]  # point id, position, distance to its net point


def _own(vec: np.ndarray) -> np.ndarray:
    """A row of its own: a view would keep the whole block it was cut from in memory."""
    return vec if vec.base is None else vec.copy()


@dataclass
class Net:
    """Net points and, for each, one real member of every group seen near it."""

    ids: list[int] = field(default_factory=list)
    vecs: list[np.ndarray] = field(default_factory=list)
    grps: list[int] = field(default_factory=list)
    reps: list[dict[int, Rep]] = field(default_factory=list)

    def __len__(self) -> int:
        return len(self.ids)

    def matrix(self, dim: int = 0) -> np.ndarray:
        return np.stack(self.vecs) if self.vecs else np.zeros((0, dim))

    def add(self, pid: int, vec: np.ndarray, grp: int, reps: dict[int, Rep] | None = None) -> None:
        vec = _own(vec)
        self.ids.append(int(pid)), self.vecs.append(vec), self.grps.append(int(grp))
        self.reps.append({int(grp): (int(pid), vec, 0.0)} if reps is None else dict(reps))

    def offer(self, at: int, grp: int, rep: Rep, policy: str) -> None:
        """Group ``grp`` occurs near net point ``at``: set its bit; replace the representative only if the policy says so."""
        held = self.reps[at].get(grp)
        if held is None or (policy == "nearest" and (rep[2], rep[0]) < (held[2], held[0])):
            self.reps[at][grp] = (rep[0], _own(rep[1]), rep[2])

    def bits(self) -> list[int]:
        return [sum(1 << g for g in r) for r in self.reps]

    def points_held(self) -> int:
        """Net points and representatives that are not net points."""
        return len(set(self.ids) | {r[0] for reps in self.reps for r in reps.values()})


def farthest_first(x: np.ndarray, k: int, m: Metric | str = "l1"):
    """(pivots, delta, radius, owner, dist): greedy centers in order, the distance at which each was added (the first: inf),
    the distance left, and each row's nearest pivot. Ends early when every row is a pivot's copy."""
    m = metric(m)
    owner, pivots, delta = np.zeros(len(x), np.int64), [0], [np.inf]
    dist = m.one_to_many(x[0], x)
    while len(pivots) < k:
        far = int(dist.argmax())
        if dist[far] <= 0:
            break
        pivots.append(far), delta.append(float(dist[far]))
        d = m.one_to_many(x[far], x)
        closer = d < dist
        dist[closer], owner[closer] = d[closer], len(pivots) - 1
    return np.array(pivots), np.array(delta), float(dist.max()), owner, dist


def farthest_first_pruned(x: np.ndarray, k: int, m: Metric | str = "l1"):
    """As ``farthest_first``; a new pivot is only compared with rows whose own pivot is nearer to it than twice their distance."""
    m = metric(m)
    owner, pivots, delta, evaluations = np.zeros(len(x), np.int64), [0], [np.inf], len(x)
    dist = m.one_to_many(x[0], x)
    while len(pivots) < k:
        far = int(dist.argmax())
        if dist[far] <= 0:
            break
        gap = m.one_to_many(x[far], x[pivots])
        rows = np.flatnonzero(gap[owner] < 2 * dist)
        pivots.append(far), delta.append(float(dist[far]))
        d = m.one_to_many(x[far], x[rows])
        evaluations += len(rows) + len(gap)
        closer = d < dist[rows]
        dist[rows[closer]], owner[rows[closer]] = d[closer], len(pivots) - 1
    return np.array(pivots), np.array(delta), float(dist.max()), owner, dist, evaluations


def net_from_assignment(x, ids, grp, centers, owner, dist, policy: str = "nearest") -> Net:
    """Group bits and representatives of chosen centers from an assignment of all rows."""
    net = Net()
    for c in centers:
        net.add(ids[c], x[c], grp[c], {} if policy == "nearest" else None)
    order = np.lexsort((ids, dist, grp, owner)) if policy == "nearest" else np.lexsort((np.arange(len(ids)), grp, owner))
    key = owner[order].astype(np.int64) * (int(grp.max(initial=0)) + 1) + grp[order]
    first = order[np.concatenate([[True], key[1:] != key[:-1]])] if len(order) else order
    for i in first:
        net.offer(int(owner[i]), int(grp[i]), (int(ids[i]), x[i], float(dist[i])), policy)
    return net


def threshold_net(x, ids, grp, radius: float, m: Metric | str = "l1", policy: str = "first") -> Net:
    """Rows in order; a row opens a net point unless an earlier one lies within ``radius`` (the earliest such one owns it)."""
    m = metric(m)
    n = len(x)
    owner, dist, centers, i = np.full(n, -1), np.zeros(n), [], 0
    while i < n:
        if owner[i] < 0:
            rest = np.flatnonzero(owner[i:] < 0) + i
            d = m.one_to_many(x[i], x[rest])
            hit = d <= radius
            owner[rest[hit]], dist[rest[hit]] = len(centers), d[hit]
            owner[i], dist[i] = len(centers), 0.0
            centers.append(i)
        i += 1
    return net_from_assignment(x, ids, grp, centers, owner, dist, policy) if n else Net()


def _earliest(x: np.ndarray, held: np.ndarray, radius: float, m: Metric, pairs: int = 4_000_000) -> tuple[np.ndarray, np.ndarray]:
    """(owner, distance): the earliest of ``held`` within ``radius`` of each row, or -1; memory is bounded by ``pairs``."""
    owner, dist = np.full(len(x), -1), np.zeros(len(x))
    step = max(1, pairs // max(1, len(held)))
    for i in range(0, len(x) if len(held) else 0, step):
        d = m.block(x[i : i + step], held)
        hit = d <= radius
        at = hit.argmax(1)
        found = hit[np.arange(len(at)), at]
        owner[i : i + step][found], dist[i : i + step][found] = at[found], d[np.arange(len(at)), at][found]
    return owner, dist


def _placed(net: Net, held: np.ndarray, x: np.ndarray, radius: float, m: Metric, open_row, cover_row) -> None:
    """Rows in order against a growing net whose positions are ``held``: each opens a net point or is covered by the earliest near one."""
    owner, dist = _earliest(x, held, radius, m)
    for i in range(len(x)):
        if owner[i] < 0:
            open_row(i)
            rest = np.flatnonzero(owner[i + 1 :] < 0) + i + 1
            if len(rest):
                d = m.one_to_many(x[i], x[rest])
                near = d <= radius
                owner[rest[near]], dist[rest[near]] = len(net) - 1, d[near]
        else:
            cover_row(i, int(owner[i]), float(dist[i]))


def extend_net(net: Net, x, ids, grp, radius: float, m: Metric | str, policy: str) -> Net:
    """Rows in order against a growing net; whole blocks are covered at once."""
    m = metric(m)
    _placed(
        net, net.matrix(x.shape[1]), x, radius, m,
        lambda i: net.add(ids[i], x[i], grp[i]),
        lambda i, at, d: net.offer(at, int(grp[i]), (int(ids[i]), x[i], d), policy),
    )
    return net


def merge_nets(fine: Net, coarse: Net, radius: float, m: Metric | str = "l1", alpha: float = 1.0, policy: str = "first", rows: int = 256) -> Net:
    """Absorb the finer net into the coarser one at ``alpha * radius``; with an empty coarse net this re-nets the fine one."""
    m = metric(m)
    out = Net(list(coarse.ids), list(coarse.vecs), list(coarse.grps), [dict(r) for r in coarse.reps])

    def absorb(i: int, at: int) -> None:
        for g, (rid, rvec, _) in sorted(fine.reps[i].items()):
            out.offer(at, g, (rid, rvec, float(m.block(rvec[None], out.vecs[at][None])[0, 0])), policy)

    for a in range(0, len(fine), rows):
        x = np.stack(fine.vecs[a : a + rows])
        _placed(out, out.matrix(x.shape[1]), x, alpha * radius, m, lambda i, a=a: out.add(fine.ids[a + i], fine.vecs[a + i], fine.grps[a + i], fine.reps[a + i]), lambda i, at, d, a=a: absorb(a + i, at))
    return out


def spread_subset(x: np.ndarray, gap: float, m: Metric, most: int | None = None) -> list[int]:
    """Greedy maximal subset in row order with pairwise distances above ``gap``; with ``most``, one row more than that ends it."""
    kept: list[int] = []
    near = np.full(len(x), np.inf)
    for i in range(len(x)):
        if near[i] > gap:
            kept.append(i)
            if most is not None and len(kept) > most:
                break
            near[i + 1 :] = np.minimum(near[i + 1 :], m.one_to_many(x[i], x[i + 1 :])) if i + 1 < len(x) else near[i + 1 :]
    return kept


def _least_positive_gap(x: np.ndarray, m: Metric) -> float:
    best = np.inf
    for i in range(1, len(x)):
        d = m.one_to_many(x[i], x[:i])
        d = d[d > 0]
        if len(d):
            best = min(best, float(d.min()))
    return best


class BudgetNet:
    """At most ``budget`` centers over a stream, with representatives; ``r`` bounds the optimal radius of ``budget`` centers from below.

    Once r > 0: centers are more than 4r apart and every row seen is within 8r of one. A row that is covered joins its nearest center.
    """

    def __init__(self, budget: int, m: Metric | str = "l1", policy: str = "nearest"):
        self.budget, self.m, self.policy = budget, metric(m), policy
        self.net, self.r, self.seen, self.doublings, self.held_most, self.packed = Net(), 0.0, 0, 0, 0, False

    def insert_block(self, x: np.ndarray, ids: np.ndarray, grp: np.ndarray, step: int = 2048) -> None:
        for i in range(0, len(x), step):
            self._block(x[i : i + step], ids[i : i + step], grp[i : i + step])

    def insert(self, pid: int, grp: int, vec: np.ndarray) -> None:
        self._block(np.asarray(vec, float)[None], np.array([pid]), np.array([grp]))

    def _nearest(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if not len(self.net):
            return np.zeros(len(x), np.int64), np.full(len(x), np.inf)
        d = self.m.block(x, self.net.matrix())
        return d.argmin(1), d.min(1)

    def _positions(self) -> np.ndarray | PackedRows:
        return PackedRows.of_dense(self.net.matrix()) if self.packed else self.net.matrix()

    def _block(self, x, ids, grp) -> None:
        self.seen += len(x)
        self.packed = isinstance(x, PackedRows)
        owner, dist = self._nearest(x)
        at = 0
        while at < len(x):
            out = np.flatnonzero(dist[at:] > 8 * self.r)
            stop = at + int(out[0]) if len(out) else len(x)
            self._cover(x[at:stop], ids[at:stop], grp[at:stop], owner[at:stop], dist[at:stop])
            at = stop
            if at == len(x):
                break
            self.net.add(ids[at], x[at], grp[at])
            before = self.r
            if len(self.net) > self.budget:
                self._overflow()
            at += 1
            if self.r != before:
                owner[at:], dist[at:] = self._nearest(x[at:])
            elif at < len(x):
                d = self.m.one_to_many(self.net.vecs[-1], x[at:])
                closer = d < dist[at:]
                dist[at:][closer], owner[at:][closer] = d[closer], len(self.net) - 1
        self.held_most = max(self.held_most, self.net.points_held()) if self.policy else 0

    def _cover(self, x, ids, grp, owner, dist) -> None:
        if not len(x) or not self.policy:
            return
        order = np.lexsort((np.arange(len(x)), ids, dist, grp, owner)) if self.policy == "nearest" else np.lexsort((np.arange(len(x)), grp, owner))
        key = owner[order].astype(np.int64) * (1 << 20) + grp[order]
        for i in order[np.concatenate([[True], key[1:] != key[:-1]])]:
            self.net.offer(int(owner[i]), int(grp[i]), (int(ids[i]), x[i], float(dist[i])), self.policy)

    def _overflow(self) -> None:
        if self.policy:
            self.held_most = max(self.held_most, self.net.points_held())
        x = self._positions()
        start = 1
        if self.r == 0:
            self.r, start = _least_positive_gap(x, self.m) / 2, 0
        lam = start
        while len(kept := spread_subset(x, 4 * 2.0**lam * self.r, self.m, self.budget)) > self.budget:
            lam += 1
        self.r *= 2.0**lam
        self.doublings += lam
        old = self.net
        self.net = Net([old.ids[i] for i in kept], [old.vecs[i] for i in kept], [old.grps[i] for i in kept], [old.reps[i] for i in kept])
        held = self._positions()
        for i in sorted(set(range(len(old))) - set(kept)):
            d = self.m.one_to_many(old.vecs[i], held)
            to = int(d.argmin())
            for g, (rid, rvec, _) in sorted(old.reps[i].items()):
                self.net.offer(to, g, (rid, rvec, float(self.m.block(rvec[None], held[to][None])[0, 0])), self.policy or "first")


class RadiusTracker:
    """Lower bound r(t) on the optimal radius of k centers over a stream (a budget net of k without representatives)."""

    def __init__(self, k: int, m: Metric | str = "l1"):
        self._net = BudgetNet(k, m, policy="")

    def offer(self, vec: np.ndarray) -> bool:
        """Take one more row; whether r grew."""
        before = self._net.r
        self._net.insert(self._net.seen, 0, vec)
        return self._net.r > before

    @property
    def r(self) -> float:
        return self._net.r

    @property
    def centers(self) -> np.ndarray:
        return self._net.net.matrix()

    @property
    def doublings(self) -> int:
        return self._net.doublings


class IncrementalNet:
    """Guaranteed one-pass net: packing eps_bar * r / 2, covering eps_bar * r, for the tracker's current r.

    When r grows, the net is re-netted at the new radius before the row is placed. Until r > 0 all distinct rows are kept.
    """

    def __init__(self, k: int, eps_bar: float, m: Metric | str = "l1", policy: str = "first", max_net: int = 200_000):
        self.tracker, self.eps_bar, self.m, self.policy, self.max_net = RadiusTracker(k, m), eps_bar, metric(m), policy, max_net
        self.net, self.seen, self.held_most = Net(), 0, 0

    @property
    def r(self) -> float:
        return self.tracker.r

    def insert(self, pid: int, grp: int, vec: np.ndarray) -> None:
        self.insert_block(np.asarray(vec, float)[None], np.array([pid]), np.array([grp]))

    def insert_block(self, x, ids, grp, step: int = 4096) -> None:
        """Rows that the tracker covers cannot move r, so they are placed as one block; the others go one by one."""
        for i in range(0, len(x), step):
            self._block(x[i : i + step], ids[i : i + step], grp[i : i + step])

    def _block(self, x, ids, grp) -> None:
        at, far = 0, self._far(x)
        while at < len(x):
            out = np.flatnonzero(far[at:] > 8 * self.r)
            stop = at + int(out[0]) if len(out) else len(x)
            self._place(x[at:stop], ids[at:stop], grp[at:stop])
            if (at := stop) == len(x):
                break
            if grew := self.tracker.offer(x[at]):
                self.net = merge_nets(self.net, Net(), self.eps_bar * self.r / 2, self.m, alpha=1.0, policy=self.policy)
            self._place(x[at : at + 1], ids[at : at + 1], grp[at : at + 1])
            at += 1
            far[at:] = self._far(x[at:]) if grew else np.minimum(far[at:], self.m.one_to_many(x[at - 1], x[at:])) if at < len(x) else far[at:]
        self.held_most = max(self.held_most, self.net.points_held())

    def _far(self, x) -> np.ndarray:
        c = self.tracker.centers
        return self.m.block(x, c).min(1) if len(c) and len(x) else np.full(len(x), np.inf)

    def _place(self, x, ids, grp) -> None:
        self.seen += len(x)
        if len(x):
            extend_net(self.net, x, ids, grp, self.eps_bar * self.r, self.m, self.policy)
        if len(self.net) > self.max_net:
            raise ValueError(f"net exceeds {self.max_net} points: eps is too small for this dimension; use the budgeted method")


def nearest_by_group(x, ids, grp, centers, m: Metric | str = "l1"):
    """(center, group, distance, row) of the nearest member of each group for each center, ties to the smaller id."""
    m, order = metric(m), np.lexsort((ids, grp))
    x, sorted_grp = x[order], grp[order]
    cuts = np.flatnonzero(np.diff(sorted_grp, prepend=sorted_grp[:1] - 1)) if len(order) else np.zeros(0, np.int64)
    for j in range(len(centers)):
        d = m.one_to_many(centers[j], x)
        for a, b in zip(cuts, np.append(cuts[1:], len(order))):
            at = a + int(d[a:b].argmin())
            yield j, int(sorted_grp[a]), float(d[at]), int(order[at])


def min_dist_block(x: np.ndarray, c: np.ndarray, m: Metric | str = "l1", rows: int = 8192) -> tuple[np.ndarray, np.ndarray]:
    """(least distance, index of the first nearest center) of each row, in chunks."""
    m, best, at = metric(m), [], []
    for i in range(0, len(x), rows):
        d = m.block(x[i : i + rows], c)
        best.append(d.min(1)), at.append(d.argmin(1))
    return (np.concatenate(best), np.concatenate(at)) if best else (np.zeros(0), np.zeros(0, np.int64))
