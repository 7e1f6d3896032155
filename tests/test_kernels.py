import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from evenpick.functions.kernels import BudgetNet, IncrementalNet, Net, RadiusTracker, farthest_first, farthest_first_pruned, merge_nets, min_dist_block, threshold_net
from evenpick.functions.matching import hall_feasible, match_pivots, saturates
from evenpick.functions.metrics import METRICS
from evenpick.functions.solver import solve_exact, solve_static


def cloud(seed, n=24, groups=3, heavy=False, copies=False):
    rng = np.random.default_rng(seed)
    x = rng.normal(size=(n, 2)) * (rng.pareto(1.5, (n, 1)) + 0.2 if heavy else 1)
    if copies:
        x[5:10] = x[:5]
    return x, np.arange(n), rng.integers(0, groups, n)


def gaps(y):
    return np.abs(y[:, None] - y[None]).sum(2)[np.triu_indices(len(y), 1)] if len(y) > 1 else np.array([np.inf])


@pytest.mark.parametrize("seed", range(40))
def test_static_within_three_and_feasible(seed):
    x, _, g = cloud(seed, heavy=seed % 2 == 1, copies=seed % 3 == 0)
    caps = {0: 1, 1: seed % 3, 2: 2}
    best = solve_exact(x, g, caps).radius
    got = solve_static(x, g, caps)
    filled = solve_static(x, g, caps, fill="greedy")
    cost = min_dist_block(x, x[got.rows])[0].max()
    assert cost <= 3 * best + 1e-9
    assert min_dist_block(x, x[filled.rows])[0].max() <= cost + 1e-9
    for rows in (got.rows, filled.rows):
        assert len(set(rows)) == len(rows)
        assert all((g[rows] == k).sum() <= c for k, c in caps.items())


@pytest.mark.parametrize("seed", range(25))
def test_budget_net_invariants_hold_after_every_row_and_blocks_agree(seed):
    x, ids, g = cloud(seed, 60, heavy=seed % 2 == 1, copies=seed % 3 == 0)
    one, block = BudgetNet(8), BudgetNet(8)
    for i in range(len(x)):
        one.insert(ids[i], g[i], x[i])
        if one.r > 0:
            y = one.net.matrix()
            assert len(y) <= 8 and gaps(y).min() > 4 * one.r
            assert min_dist_block(x[: i + 1], y)[0].max() <= 8 * one.r + 1e-9
    block.insert_block(x, ids, g)
    assert block.net.ids == one.net.ids and block.r == one.r
    assert [{k: v[0] for k, v in r.items()} for r in block.net.reps] == [{k: v[0] for k, v in r.items()} for r in one.net.reps]
    assert {k for r in one.net.reps for k in r} == set(g)


@pytest.mark.parametrize("seed", range(20))
def test_tracker_bounds_the_optimum_and_incremental_net_is_proper(seed):
    x, ids, g = cloud(seed, 40, heavy=seed % 2 == 1)
    k, eps = 3, 0.5
    net, tracker = IncrementalNet(k, eps), RadiusTracker(k)
    for i in range(len(x)):
        tracker.offer(x[i])
        net.insert(ids[i], g[i], x[i])
        if net.r > 0:
            y = net.net.matrix()
            assert gaps(y).min() >= eps * net.r / 2 - 1e-12
            assert min_dist_block(x[: i + 1], y)[0].max() <= eps * net.r + 1e-9
    assert net.r == tracker.r
    assert tracker.r <= solve_exact(x, np.zeros(len(x), int), {0: k}).radius + 1e-9


@pytest.mark.parametrize("seed", range(20))
def test_merge_keeps_packing_covering_and_groups(seed):
    x, ids, g = cloud(seed, 50)
    r = 0.3
    fine, coarse = threshold_net(x[:25], ids[:25], g[:25], r), threshold_net(x[25:], ids[25:], g[25:], 2 * r)
    out = merge_nets(fine, coarse, 2 * r)
    assert gaps(out.matrix()).min() > 2 * r
    assert min_dist_block(x, out.matrix())[0].max() <= 4 * r + 1e-9
    assert {k for reps in out.reps for k in reps} == set(g)
    assert all(g[p] == k for reps in out.reps for k, (p, _, _) in reps.items())
    alone = merge_nets(fine, Net(), 2 * r)
    assert gaps(alone.matrix()).min() > 2 * r


@pytest.mark.parametrize("name", list(METRICS))
def test_metrics_are_metrics(name):
    rng = np.random.default_rng(1)
    x = (rng.random((12, 6)) < 0.5).astype(float) if name in ("jaccard", "hamming", "inversions") else rng.normal(size=(12, 6))
    d = METRICS[name].block(x, x)
    assert np.allclose(d, d.T) and np.allclose(np.diag(d), 0, atol=1e-7)
    for a in range(12):
        assert (d[a][None, :] <= d[a][:, None] + d + 1e-9).all()


@given(st.lists(st.sets(st.integers(0, 3), max_size=4), max_size=6), st.lists(st.integers(0, 2), min_size=4, max_size=4))
@settings(max_examples=200, deadline=None)
def test_matching_agrees_with_hall(adj, caps):
    caps = dict(enumerate(caps))
    lists = [[g for g in sorted(a) if caps[g] > 0] for a in adj]
    ok = saturates(lists, caps)
    assert ok == hall_feasible([sum(1 << g for g in a) for a in lists], caps)
    chosen = match_pivots(lists, caps)
    assert (chosen is not None) == ok
    if ok:
        assert all(c in a for c, a in zip(chosen, lists)) and all(chosen.count(g) <= c for g, c in caps.items())


def test_line_of_points_by_hand():
    x = np.arange(100, dtype=float)[:, None]
    p, delta, radius, owner, dist = farthest_first(x, 3)
    assert p.tolist() == [0, 99, 49] and delta[1:].tolist() == [99, 49] and radius == 25
    q = farthest_first_pruned(x, 3)
    assert (q[0] == p).all() and (q[4] == dist).all() and q[5] < 300


def test_edges():
    x = np.zeros((4, 2))
    assert len(farthest_first(x, 3)[0]) == 1
    net = BudgetNet(2)
    net.insert_block(x, np.arange(4), np.array([0, 1, 0, 1]))
    assert len(net.net) == 1 and set(net.net.reps[0]) == {0, 1} and net.r == 0
    with pytest.raises(ValueError):
        solve_static(x, np.zeros(4, int), {0: 0})
    assert len(solve_static(x, np.zeros(4, int), {0: 9}).rows) == 1
    far = np.array([[2.0**i] for i in range(12)])
    geo = BudgetNet(3)
    geo.insert_block(far, np.arange(12), np.zeros(12, int))
    assert geo.doublings > 3 and len(geo.net) <= 3
