"""One-pass selection over an ordered stream: guaranteed and budgeted nets, checkpoints, and sharded runs merged on query."""

from __future__ import annotations

import time
from collections.abc import Mapping
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evenpick.functions.kernels import BudgetNet, IncrementalNet, farthest_first, min_dist_block
from evenpick.functions.metrics import Metric, metric
from evenpick.functions.solver import check_caps, solve_static
from evenpick.operators.baselines import two_pass_local
from evenpick.operators.distributed import coordinator_net
from evenpick.operators.frames import NET, SUMMARY, in_order, net_rows, per_shard_stream, shard_points, shards_for
from evenpick.operators.nets import solve_on_net
from evenpick.plans.durable import staged

TRACE = "n_seen long, r double, net_points long, points_held long, doublings long"
CHECKPOINT = "n_seen long, cost double, greedy_radius double, points_held long, t_update double, t_solve double, t_scratch double, two_pass_cost double, two_pass_held long, t_two_pass double"


def one_pass_net(points: DataFrame, k: int, eps_bar: float, m: Metric | str = "l1", order=("point_id",)) -> DataFrame:
    """NET of one ordered replay with a guaranteed covering of eps_bar * r(t)."""
    name = metric(m).name

    def run(blocks):
        net = IncrementalNet(k, eps_bar, name)
        for x, ids, grp in blocks:
            net.insert_block(x, ids, grp)
        yield net_rows(net.net)

    return in_order(points, list(order), run, NET)


def one_pass_budget_net(points: DataFrame, budget: int, m: Metric | str = "l1", order=("point_id",), reps: str = "nearest", counted: bool = False) -> DataFrame:
    """NET of one ordered replay with at most ``budget`` centers; ``counted`` adds ``held_most``, the most points ever held."""
    name = metric(m).name

    def run(blocks):
        net = BudgetNet(budget, name, reps)
        for x, ids, grp in blocks:
            net.insert_block(x, ids, grp)
        rows = net_rows(net.net)
        yield rows.assign(held_most=net.held_most) if counted else rows

    return in_order(points, list(order), run, NET + ", held_most long" if counted else NET)


def one_pass_fair_centers(points: DataFrame, caps: Mapping[int, int], eps: float = 1.0, m: Metric | str = "l1", order=("point_id",), solver="static") -> DataFrame:
    """CENTER within 3(1 + eps) of the optimum from one pass."""
    caps = check_caps(caps)
    return solve_on_net(one_pass_net(points, sum(caps.values()), eps / 3, m, order), caps, solver, m)


def one_pass_fair_centers_budget(points: DataFrame, caps: Mapping[int, int], budget: int = 240, m: Metric | str = "l1", order=("point_id",), solver="static", located: str = "rep", fill: str = "none") -> DataFrame:
    """CENTER from one pass in the memory of ``budget`` centers with one representative per group."""
    caps = check_caps(caps)
    return solve_on_net(one_pass_budget_net(points, budget, m, order), caps, solver, m, located=located, fill=fill)


def sharded_nets(points: DataFrame, k: int, eps_bar: float, shards: int, m: Metric | str = "l1", how: str = "hash") -> DataFrame:
    """SUMMARY of ``shards`` parallel one-pass nets (rows of a shard in id order); r_t is each net's radius.

    The merge doubles the largest radius, so shards run at half of ``eps_bar``.
    """
    name = metric(m).name

    def finish(shard, net):
        return net_rows(net.net, shard=shard, r_t=net.r, n_t=net.seen)

    return per_shard_stream(shard_points(points, shards, how), lambda: IncrementalNet(k, eps_bar / 2, name), finish, SUMMARY)


def sharded_fair_centers(points: DataFrame, caps: Mapping[int, int], eps: float = 1.0, shards: int | None = None, m: Metric | str = "l1", how: str = "hash", solver="static") -> DataFrame:
    """CENTER from parallel one-pass nets merged on query: net radius eps_bar/2 * max r, so packing and covering add up to 3(1 + eps)."""
    caps = check_caps(caps)
    nets = staged(sharded_nets(points, sum(caps.values()), eps / 3, shards_for(points, shards), m, how), "sharded-nets")
    return solve_on_net(coordinator_net(nets, eps / 3 / 4, m), caps, solver, m)


def budget_trace(points: DataFrame, budget: int, every: int, m: Metric | str = "l1", order=("point_id",)) -> DataFrame:
    """State after every ``every`` rows of the budgeted pass: radius, centers, points held, doublings."""
    name = metric(m).name

    def run(blocks):
        net, out = BudgetNet(budget, name), []
        for x, ids, grp in blocks:
            at = 0
            while at < len(x):
                take = min(len(x) - at, every - net.seen % every)
                net.insert_block(x[at : at + take], ids[at : at + take], grp[at : at + take])
                at += take
                if net.seen % every == 0:
                    out.append((net.seen, net.r, len(net.net), net.net.points_held(), net.doublings))
        if net.seen % every:
            out.append((net.seen, net.r, len(net.net), net.net.points_held(), net.doublings))
        yield pd.DataFrame(out, columns=[c.split()[0] for c in TRACE.split(", ")])

    return in_order(points, list(order), run, TRACE)


def checkpoint_costs(points: DataFrame, caps: Mapping[int, int], every: int = 2500, upto: int | None = None, budget: int = 240, m: Metric | str = "l1", order=("point_id",), restart: bool = False, two_pass: bool = False, eps: float = 0.1) -> DataFrame:
    """CHECKPOINT rows of the budgeted pass: cost and greedy radius on the prefix, update and solve seconds, (``restart``) a replay from scratch, and (``two_pass``) the two-pass baseline
    run anew on the prefix.

    The prefix itself is kept by the measuring task only because cost and normaliser are defined on it; the method holds the net.
    """
    caps, name = check_caps(caps), metric(m).name

    def solve(net):
        held = {p: (v, g) for r in net.net.reps for g, (p, v, _) in r.items()}
        ids = sorted(held)
        x, grp = np.stack([held[i][0] for i in ids]), np.array([held[i][1] for i in ids])
        return x[solve_static(x, grp, caps, name).rows]

    def run(blocks):
        net, out, seen, update = BudgetNet(budget, name), [], [], 0.0
        for x, ids, grp in blocks:
            at = 0
            while at < len(x) and (upto is None or net.seen < upto):
                take = min(len(x) - at, every - net.seen % every, (upto or 1 << 60) - net.seen)
                part = x[at : at + take], ids[at : at + take], grp[at : at + take]
                began = time.perf_counter()
                net.insert_block(*part)
                update += time.perf_counter() - began
                seen.append(part)
                at += take
                if net.seen % every == 0:
                    began = time.perf_counter()
                    centers = solve(net)
                    solved = time.perf_counter() - began
                    x_, i_, g_ = (np.concatenate(c) for c in zip(*seen))
                    scratch = float("nan")
                    if restart:
                        began = time.perf_counter()
                        again = BudgetNet(budget, name)
                        again.insert_block(x_, i_, g_)
                        solve(again)
                        scratch = time.perf_counter() - began
                    other = (None, None, None)
                    if two_pass:
                        began = time.perf_counter()
                        rows, held = two_pass_local(x_, i_, g_, caps, eps, name)
                        took = time.perf_counter() - began
                        other = (float(min_dist_block(x_, x_[rows], name)[0].max()), held, took)
                    radius = farthest_first(x_, sum(caps.values()), name)[2]
                    net.held_most = max(net.held_most, net.net.points_held())
                    out.append((net.seen, float(min_dist_block(x_, centers, name)[0].max()), radius, net.held_most, update, solved, scratch, *other))
                    update = 0.0
        yield pd.DataFrame(out, columns=[c.split()[0] for c in CHECKPOINT.split(", ")])

    return in_order(points, list(order), run, CHECKPOINT)


def mean_checkpoints(points: DataFrame, caps: Mapping[int, int], repeats: int = 3, **kw) -> DataFrame:
    """CHECKPOINT rows with all seconds as means of ``repeats`` runs; everything else is the same in every run."""
    runs = [checkpoint_costs(points, caps, **kw) for _ in range(repeats)]
    rows = staged(reduce(DataFrame.union, runs), "checkpoints")
    names = [c.split()[0] for c in CHECKPOINT.split(", ")]
    return rows.groupBy("n_seen").agg(*[(F.avg if n.startswith("t_") else F.max)(n).alias(n) for n in names[1:]]).select(*names).orderBy("n_seen")
