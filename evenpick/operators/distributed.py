"""One-round distributed selection: guaranteed and budgeted workers, coordinator by a tree of net merges.

Workers read their shard once and send a net; what crosses the network is the nets. At very many workers the merge is a tree: the
absorbing radii of its levels halve from the top, so their sum stays below twice the last and the guarantee is kept.
"""

from __future__ import annotations

from collections.abc import Mapping

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evenpick.functions import kernels
from evenpick.functions.kernels import BudgetNet, Net, farthest_first, net_from_assignment
from evenpick.functions.metrics import Metric, metric
from evenpick.functions.solver import check_caps
from evenpick.operators.frames import NET, SUMMARY, matrix, net_of, net_rows, per_shard, shard_points, shards_for
from evenpick.operators.nets import solve_on_net
from evenpick.plans.durable import ship_package, staged

FAN_IN = 256


def worker_net(points: DataFrame, k: int, eps_bar: float, shards: int, m: Metric | str = "l1", how: str = "hash", reps: str = "first") -> DataFrame:
    """SUMMARY of every shard: r_t is an eighth of its greedy radius for k centers, its net covers at 2 * eps_bar * r_t."""
    name = metric(m).name

    def run(shard, x, ids, grp):
        r = farthest_first(x, k, name)[2] / 8
        return net_rows(kernels.threshold_net(x, ids, grp, 2 * eps_bar * r, name, reps), shard=shard, r_t=r, n_t=len(x))

    return per_shard(shard_points(points, shards, how), run, SUMMARY)


def worker_budget(points: DataFrame, budget: int, shards: int, m: Metric | str = "l1", how: str = "hash", reps: str = "nearest") -> DataFrame:
    """SUMMARY of every shard: ``budget`` greedy centers, all points assigned to the nearest; r_t is the coverage radius."""
    name = metric(m).name

    def run(shard, x, ids, grp):
        p, _, radius, owner, dist = farthest_first(x, budget, name)
        return net_rows(net_from_assignment(x, ids, grp, p, owner, dist, reps), shard=shard, r_t=radius, n_t=len(x))

    return per_shard(shard_points(points, shards, how), run, SUMMARY)


def worker_scan(points: DataFrame, budget: int, m: Metric | str = "l1", reps: str = "nearest") -> DataFrame:
    """SUMMARY of every input split by one streaming scan: no exchange of points, memory of one budget net.

    A shard here is whatever a task reads, so results depend on the splits; use the sharded worker where runs must be comparable.
    """
    name = metric(m).name
    ship_package(points.sparkSession)

    def run(batches):
        net = BudgetNet(budget, name, reps)
        first = None
        for b in batches:
            if len(b):
                first = int(b.point_id.iloc[0]) if first is None else first
                net.insert_block(matrix(b.vec.to_numpy()), b.point_id.to_numpy(np.int64), b.grp.to_numpy(np.int64))
        if first is not None:
            yield net_rows(net.net, shard=first, r_t=8 * net.r, n_t=net.seen)

    return points.select("point_id", "grp", "vec").mapInPandas(run, SUMMARY)


def coordinator_net(summaries: DataFrame, eps_bar: float, m: Metric | str = "l1", levels: int = 1, fan_in: int = FAN_IN, reps: str = "first") -> DataFrame:
    """NET of all shards. One level folds all workers at eps_bar * R, R twice the largest r_t; more levels fold ``fan_in`` at a time."""
    name = metric(m).name
    ship_package(summaries.sparkSession)
    most = float(summaries.agg(F.max("r_t")).first()[0] or 0.0)
    radii = [2 * eps_bar * most] if levels == 1 else [eps_bar * most / 2 ** (levels - 1 - i) for i in range(levels)]
    rank = summaries.select("shard", "net_id", "vec", "grp", "groups", "reps").withColumn("place", F.col("net_id"))
    for i, radius in enumerate(radii):
        bucket = F.lit(0).cast("long") if i == levels - 1 else F.floor(F.col("shard") / fan_in).cast("long")

        rank = rank.withColumn("bucket", bucket).groupBy("bucket").applyInPandas(_fold(radius, name, reps), f"shard long, {NET}, place long")
    return rank.select("net_id", "vec", "grp", "groups", "reps")


def _fold(radius: float, name: str, policy: str):
    """Fold the nets of a bucket, shard after shard."""

    def fold(pdf: pd.DataFrame) -> pd.DataFrame:
        out = Net()
        for _, part in sorted(pdf.groupby("shard")):
            out = kernels.merge_nets(net_of(part.sort_values("place", kind="stable")), out, radius, name, 1.0, policy)
        rows = net_rows(out, shard=int(pdf.bucket.iloc[0]))
        return rows.assign(place=np.arange(len(rows)))

    return fold


def budget_tree(summaries: DataFrame, budget: int, m: Metric | str = "l1", fan_in: int = FAN_IN) -> DataFrame:
    """SUMMARY of merged shards: greedy centers among the representatives of ``fan_in`` workers; coverage radii add up in r_t."""
    name = metric(m).name
    reps = summaries.select("shard", "r_t", "n_t", F.explode("reps").alias("r")).withColumn("bucket", F.floor(F.col("shard") / fan_in))

    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        r = pdf.r.map(lambda x: (x["point_id"], x["grp"], np.asarray(x["vec"], float)))
        seen = {p: (g, v) for p, g, v in r}
        ids = np.array(sorted(seen))
        x, grp = np.stack([seen[i][1] for i in ids]), np.array([seen[i][0] for i in ids])
        p, _, radius, owner, dist = farthest_first(x, budget, name)
        n = int(pdf.drop_duplicates("shard").n_t.sum())
        return net_rows(net_from_assignment(x, ids, grp, p, owner, dist, "nearest"), shard=int(key[0]), r_t=radius + float(pdf.r_t.max()), n_t=n)

    ship_package(summaries.sparkSession)
    return reps.groupBy("bucket").applyInPandas(run, SUMMARY)


def distributed_fair_centers(points: DataFrame, caps: Mapping[int, int], eps: float = 1.0, shards: int | None = None, m: Metric | str = "l1", how: str = "hash", solver="static", levels: int | None = None, fill: str = "none") -> DataFrame:
    """CENTER within 3(1 + eps) of the optimum, in one communication round.

    ``shards=None`` sizes the shards by the data; ``levels=None`` adds merge levels as the shards grow past ``FAN_IN``.
    """
    caps = check_caps(caps)
    shards = shards_for(points, shards)
    while levels is None or FAN_IN**levels < shards:
        levels = (levels or 0) + 1
    nets = staged(worker_net(points, sum(caps.values()), eps / 3, shards, m, how), "worker-nets")
    return solve_on_net(coordinator_net(nets, eps / 3, m, levels), caps, solver, m, fill=fill)


def distributed_fair_centers_budget(
    points: DataFrame, caps: Mapping[int, int], budget: int = 24, shards: int | None = None, m: Metric | str = "l1", how: str = "hash", located: str = "rep",
    worker: str = "buffered", budget_total: int | None = None, solver="static", fill: str = "none", merge: bool = False,
) -> DataFrame:
    """CENTER from ``budget`` greedy centers per shard (or ``budget_total`` over all), solved on the real representatives.

    ``shards=None`` sizes the shards by the data; ``worker='single_scan'`` needs no shards at all. ``merge`` asks for greedy centers of groups of workers
    in between (fewer points for the solver, a larger coverage radius); without it the solver takes whatever the workers send.
    """
    caps = check_caps(caps)
    shards = shards_for(points, shards) if worker == "buffered" or budget_total else 1
    if budget_total:
        budget = max(1, budget_total // shards)
    sent = worker_scan(points, budget, m) if worker == "single_scan" else worker_budget(points, budget, shards, m, how)
    sent = staged(sent, "worker-budgets")
    if merge:
        sent = staged(budget_tree(sent, budget, m), "merged-budgets")
    return solve_on_net(sent.select("net_id", "vec", "grp", "groups", "reps"), caps, solver, m, located=located, fill=fill)


def budget_run(points: DataFrame, caps: Mapping[int, int], budget_total: int, shards: int, m: Metric | str = "l1", how: str = "hash") -> tuple[DataFrame, int]:
    """(CENTER, points that the workers send) of the budgeted method."""
    sent = staged(worker_budget(points, max(1, budget_total // shards), shards, m, how), "worker-budgets")
    held = sent.select(F.explode("reps.point_id").alias("id")).agg(F.count_distinct("id")).first()[0]
    return solve_on_net(sent.select("net_id", "vec", "grp", "groups", "reps"), check_caps(caps), "static", m, located="rep"), held


def budget_sufficient(coverage: float, lower_bound: float, eps: float) -> bool:
    """Whether the coverage radius is small enough for 3(1 + eps), with a lower bound in place of the optimum."""
    return coverage <= eps / 3 * lower_bound


def coverage_by_budget(points: DataFrame, budgets: list[int], shards: int = 10, m: Metric | str = "l1", how: str = "hash") -> DataFrame:
    """(shard, budget, radius): coverage radius of every budget, all from one greedy run (a smaller budget is a prefix)."""
    name = metric(m).name
    budgets = sorted(budgets)

    def run(shard, x, ids, grp):
        _, delta, radius, _, _ = farthest_first(x, budgets[-1] + 1, name)
        after = [*delta[1:].tolist(), radius]
        return pd.DataFrame({"shard": shard, "budget": np.array(budgets, np.int64), "radius": [after[b - 1] if b - 1 < len(after) else 0.0 for b in budgets]})

    return per_shard(shard_points(points, shards, how), run, "shard long, budget long, radius double")


def smallest_budget(points: DataFrame, budgets: list[int], eps: float, k: int, shards: int = 10, m: Metric | str = "l1", how: str = "hash") -> int | None:
    """The least of ``budgets`` whose coverage suffices on every shard, judged by the greedy lower bound for k centers."""
    table = coverage_by_budget(points, sorted({*budgets, k}), shards, m, how).groupBy("budget").agg(F.max("radius").alias("r")).collect()
    got = {r.budget: r.r for r in table}
    return next((b for b in sorted(budgets) if budget_sufficient(got[b], got[k] / 2, eps)), None)
