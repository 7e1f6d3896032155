"""Tables of the experiments: time and memory, cost ratios, small data, checkpoints, sweeps."""

from __future__ import annotations

import time
from collections.abc import Mapping

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenpick.operators import baselines, distributed, onepass
from evenpick.operators.frames import for_driver
from evenpick.operators.greedy import greedy_pivots, with_distance
from evenpick.operators.measures import center_vectors, costs
from evenpick.operators.nets import solve_on_net
from evenpick.operators.static import static_fair_centers
from evenpick.plans.durable import drop_staged, staged
from evenpick.sources.points import WORKLOAD_GROUPS, WORKLOADS, WORKLOADS_BY_ALL

TABLE = "workload string, groups int, method string, points long, seconds double, points_held long, cost double, greedy_radius double, ratio double, feasible boolean"


def run_method(name: str, points: DataFrame, caps: Mapping[int, int], m="l1", budget: int = 240, shards: int = 10, eps: float = 0.1, bounds=None, once: tuple[DataFrame, bool] | None = None) -> tuple[DataFrame, int]:
    """(CENTER, points held) of one method on one point set: the most that a pass holds, or what the workers send. ``once``: what ``for_driver`` gave for the points."""
    if name == "static":
        part, where = (once[0], "driver" if once[1] else "rounds") if once else (points, "auto")
        return static_fair_centers(part, caps, m, where=where), points.count()
    if name == "two_pass":
        return baselines.two_pass_run(once[0] if once else points, caps, eps, m, bounds=bounds, distinct=once is not None)
    if name == "one_pass":
        net = staged(onepass.one_pass_budget_net(points, budget, m, counted=True), "one-pass-net")
        return solve_on_net(net.drop("held_most"), caps, "static", m, located="rep"), net.first().held_most
    if name == "prior_distributed":
        return baselines.prior_distributed_run(points, caps, eps, shards, m)
    if name == "distributed":
        return distributed.budget_run(points, caps, budget, shards, m)
    if name == "random":
        return baselines.random_fair_centers(points, caps), sum(caps.values())
    raise ValueError(f"unknown method {name}")


METHODS = ("static", "two_pass", "one_pass", "prior_distributed", "distributed")


def compare(points: DataFrame, caps: Mapping[int, int], methods=METHODS, m="l1", workload: str = "", budget: int = 240, shards: int = 10, eps: float = 0.1) -> DataFrame:
    """TABLE rows: every method on one point set, with cost on all points, the greedy normaliser, time and points held."""
    return compare_groups(points.withColumnRenamed("grp", "g"), {"g": caps}, methods, m, workload, budget, shards, eps)


def compare_groups(points: DataFrame, caps: Mapping[str, Mapping[int, int]], methods=METHODS, m="l1", workload: str = "", budget: int = 240, shards: int = 10, eps: float = 0.1, owned: bool = False) -> DataFrame:
    """``compare`` of one point set under several group columns with their capacities: built once, copies dropped once where points do not fit the driver, greedy pivots run once
    (fewer centers are a prefix), all costs from one scan. ``owned``: staged tables that ``points`` reads are dropped once copied."""
    spark: SparkSession = points.sparkSession
    all_ = staged(points, "compare")
    if owned:
        drop_staged(points)
    n, most = all_.count(), max(sum(c.values()) for c in caps.values())
    once, fits = for_driver(all_, list(caps))
    pivots, last = greedy_pivots(once, most, m, fits)
    rows, vecs = [], []
    for column, cap in caps.items():
        k = sum(cap.values())
        greedy = pivots[k][2] if k < len(pivots) else last
        bounds = baselines.guess_bounds(pivots[:k], greedy, m)
        pts, part = (df.select("point_id", F.col(column).alias("grp"), "vec") for df in (all_, once))
        for name in methods:
            began = time.perf_counter()
            centers, held = run_method(name, pts, cap, m, budget, shards, eps, bounds, (part, fits))
            vecs.append(center_vectors(centers))
            seconds = time.perf_counter() - began
            used = {r.grp: r["count"] for r in centers.groupBy("grp").count().collect()}
            rows.append((workload, len(cap), name, n, seconds, held, greedy, all(c <= cap.get(g, 0) for g, c in used.items())))
    table = [(*r[:6], c, r[6], c / r[6] if r[6] else 1.0, r[7]) for r, c in zip(rows, costs(once, vecs, m))]
    return spark.createDataFrame(table, TABLE)


def workload_table(spark: SparkSession, sf_dir: str, methods=METHODS, cap: int = 10, first: int | None = None, shards: int = 10, only: dict | None = None) -> DataFrame:
    """``compare`` over all workloads and group counts (``first``: the small-data experiment on the first points)."""
    out = None
    for name, groups in (only or WORKLOAD_GROUPS).items():
        if name in WORKLOADS_BY_ALL:
            sets = [(WORKLOADS_BY_ALL[name](spark, sf_dir, groups), {f"g{g}": dict.fromkeys(range(g), cap) for g in groups})]
        else:
            sets = [(WORKLOADS[name](spark, sf_dir, g).withColumnRenamed("grp", "g"), {"g": dict.fromkeys(range(g), cap)}) for g in groups]
        for pts, caps in sets:
            if first:
                pts = pts.orderBy("point_id").limit(first)
            part = compare_groups(pts, caps, methods, workload=name, shards=shards, owned=True)
            out = part if out is None else out.union(part)
    return out


def budget_sweep(points: DataFrame, caps: Mapping[int, int], budgets=(24, 60, 120, 240, 480), shards: int = 10, m="l1", how: str = "hash") -> DataFrame:
    """(budget, coverage, cost): how coverage radius and cost move with the coreset size per shard."""
    pts = staged(points, "sweep")
    cover = {r.budget: r.radius for r in distributed.coverage_by_budget(pts, list(budgets), shards, m, how).groupBy("budget").agg(F.max("radius").alias("radius")).collect()}
    rows = []
    for b in budgets:
        vecs = center_vectors(distributed.distributed_fair_centers_budget(pts, caps, b, shards, m, how))
        rows.append((b, float(cover[b]), float(with_distance(pts, vecs, m, "d").agg(F.max("d")).first()[0])))
    return points.sparkSession.createDataFrame(rows, "budget int, coverage double, cost double")


def eps_sweep(points: DataFrame, caps: Mapping[int, int], values=(3.0, 1.0, 0.5), shards: int = 4, m="l1", how: str = "hash") -> DataFrame:
    """(eps, net_points, cost): size of the guaranteed net and cost by eps."""
    pts = staged(points, "sweep")
    rows = []
    for e in values:
        nets = staged(distributed.worker_net(pts, sum(caps.values()), e / 3, shards, m, how), "worker-nets")
        net = staged(distributed.coordinator_net(nets, e / 3, m), "net")
        vecs = center_vectors(solve_on_net(net, caps, "static", m))
        rows.append((e, net.count(), float(with_distance(pts, vecs, m, "d").agg(F.max("d")).first()[0])))
    return points.sparkSession.createDataFrame(rows, "eps double, net_points long, cost double")
