"""Baselines: two-pass streaming, earlier one-round distributed, exact optimum, random feasible choice."""

from __future__ import annotations

import math
from collections.abc import Mapping

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from evenpick.functions.kernels import farthest_first, nearest_by_group, spread_subset
from evenpick.functions.matching import match_pivots, saturates
from evenpick.functions.metrics import Metric, metric
from evenpick.functions.solver import check_caps, solve_exact
from evenpick.operators.frames import arrays, arrow_schema, centers_frame, dense, for_driver, in_order, per_shard, shard_points, shards_for, to_driver, whole_numbers
from evenpick.operators.greedy import greedy_pivots
from evenpick.plans.durable import ship_package, staged

GUESS = "tau double, pivot int, vec array<double>"
EDGE = "tau double, pivot int, grp int, dist double, point_id long, vec array<double>"


def guess_bounds(pivots: list[tuple[int, list[float], float]], radius: float, m: Metric | str = "l1") -> tuple[float, float]:
    """(low, high) for the guesses from greedy pivots for k centers: half their radius bounds the optimum from below, twice the first
    gap bounds the diameter. With radius 0 the pivots are all distinct positions, whose distances are then exact."""
    far = max((d for *_, d in pivots[1:]), default=1.0)
    if radius > 0:
        return radius / 3, 2 * max(far, radius)
    x = np.array([v for _, v, _ in pivots], float)
    gaps = metric(m).block(x, x)
    gaps = gaps[gaps > 0]
    return (float(gaps.min()), float(gaps.max())) if len(gaps) else (1.0, 1.0)


def guess_grid(low: float, high: float, eps: float) -> list[float]:
    """Radii from ``low`` up by (1 + eps) until ``high`` is passed."""
    steps = max(0, math.ceil(math.log(max(high, low) / low) / math.log1p(eps))) if low > 0 else 0
    return [low * (1 + eps) ** i for i in range(steps + 1)]


def _first_pass(points: DataFrame, grid: list[float], k: int, m: str, order) -> DataFrame:
    """For every guess the pivots more than twice the guess apart, in arrival order; a guess dies beyond k pivots."""

    def run(blocks):
        held: dict[float, list[np.ndarray]] = {t: [] for t in grid}
        mm = metric(m)
        for x, _, _ in blocks:
            for t in list(held):
                pivots = held[t]
                rest = np.arange(len(x))
                for p in pivots:
                    rest = rest[mm.one_to_many(p, x[rest]) > 2 * t]
                while len(rest):
                    pivots.append(x[rest[0]].copy())
                    if len(pivots) > k:
                        del held[t]
                        break
                    rest = rest[1:]
                    rest = rest[mm.one_to_many(pivots[-1], x[rest]) > 2 * t]
        rows = [(t, i, p.tolist()) for t, ps in held.items() for i, p in enumerate(ps)]
        yield pd.DataFrame(rows, columns=["tau", "pivot", "vec"]).astype({"pivot": "int32"})

    return in_order(points, list(order), run, GUESS)


def _members(points: DataFrame, pivots: pd.DataFrame, reach: float, m: str) -> DataFrame:
    """Second pass, fully parallel: per (guess, pivot, group) the nearest member within ``reach`` guesses, reduced in each task first."""
    ship_package(points.sparkSession)
    tau, pivot = pivots.tau.to_numpy(), pivots["pivot"].to_numpy()
    c, which = np.unique(np.stack(pivots.vec.to_numpy()).astype(float), axis=0, return_inverse=True)
    most, out = reach * np.array([tau[which == u].max() for u in range(len(c))]), arrow_schema(EDGE)

    def run(batches):
        best: dict[tuple[int, int], tuple[float, int, np.ndarray]] = {}
        for b in batches:
            if not b.num_rows:
                continue
            x, ids, grp = dense(b.column(2)), whole_numbers(b.column(0)), whole_numbers(b.column(1))
            for j, g, d, i in nearest_by_group(x, ids, grp, c, m):
                if d <= most[j] and ((j, g) not in best or (d, ids[i]) < best[j, g][:2]):
                    best[j, g] = (d, int(ids[i]), x[i].copy())
        rows = [(tau[p], pivot[p], g, d, i, v.tolist()) for (j, g), (d, i, v) in best.items() for p in np.flatnonzero(which == j) if d <= reach * tau[p]]
        pdf = pd.DataFrame(rows, columns=["tau", "pivot", "grp", "dist", "point_id", "vec"])
        yield from pa.Table.from_pandas(pdf, out, preserve_index=False).to_batches()

    edges = points.select("point_id", "grp", "vec").mapInArrow(run, EDGE)
    best = edges.groupBy("tau", "pivot", "grp").agg(F.min_by(F.struct("dist", "point_id", "vec"), F.struct("dist", "point_id")).alias("b"))
    return best.select("tau", "pivot", "grp", "b.dist", "b.point_id", "b.vec")


def _smallest_match(edges: pd.DataFrame, pivots: pd.DataFrame, caps) -> pd.DataFrame:
    for t in sorted(pivots.tau.unique()):
        e = edges[edges.tau == t]
        n = int((pivots.tau == t).sum())
        adj = [sorted(e.grp[e["pivot"] == i].tolist()) for i in range(n)]
        if saturates(adj, caps):
            chosen = match_pivots(adj, caps)
            rows = pd.concat([e[(e["pivot"] == i) & (e.grp == g)] for i, g in enumerate(chosen)])
            return rows.drop_duplicates("point_id")
    raise ValueError("no guess matches: no point belongs to a group with capacity")


def two_pass_fair_centers(points: DataFrame, caps: Mapping[int, int], eps: float = 0.1, m: Metric | str = "l1", order=("point_id",), bounds: tuple[float, float] | None = None) -> DataFrame:
    """CENTER within 3 + eps in two passes. ``bounds`` are the least positive and the largest distance; if missing, bounds from greedy pivots, at every size."""
    return two_pass_run(points, caps, eps, m, order, bounds)[0]


def two_pass_run(points, caps, eps=0.1, m="l1", order=("point_id",), bounds=None, distinct=False) -> tuple[DataFrame, int]:
    """(CENTER, points held over all guesses). ``distinct``: copies have been dropped already where that pays."""
    caps, name = check_caps(caps), metric(m).name
    if tuple(order) == ("point_id",) and not distinct:  # a later copy opens no pivot and is nobody's nearest member
        points = for_driver(points)[0]
    if bounds is None:
        bounds = guess_bounds(*greedy_pivots(points, sum(caps.values()), m), m)
    pivots = to_driver(_first_pass(points, guess_grid(bounds[0] / 2, bounds[1], eps), sum(caps.values()), name, order))
    edges = to_driver(_members(points, pivots, 1.0, name))
    edges = edges[edges.grp.map(lambda g: caps.get(g, 0) > 0)]
    got = _smallest_match(edges, pivots, caps)
    return centers_frame(points.sparkSession, got.point_id, got.grp, got.vec), len(pivots) + len(edges)


def two_pass_local(x, ids, grp, caps, eps: float = 0.1, m: Metric | str = "l1") -> tuple[list[int], int]:
    """(rows chosen, points held) of the two-pass baseline on arrays in arrival order; what a pivot has near is found once for all guesses."""
    mm, k = metric(m), sum(caps.values())
    p, delta, radius, _, _ = farthest_first(x, k, mm)
    bounds = guess_bounds([(int(ids[i]), x[i].tolist(), float(e)) for i, e in zip(p, delta)], radius, mm)
    guesses, held = {}, 0
    for t in guess_grid(bounds[0] / 2, bounds[1], eps):
        d, pivots = np.full(len(x), np.inf), []
        while len(far := np.flatnonzero(d > 2 * t)) and len(pivots) <= k:
            pivots.append(int(far[0]))
            d = np.minimum(d, mm.one_to_many(x[far[0]], x))
        if len(pivots) <= k:
            guesses[t] = pivots
    every = sorted({i for ps in guesses.values() for i in ps})
    near: dict[int, list[tuple[int, float, int]]] = {i: [] for i in every}
    for j, g, d, i in nearest_by_group(x, ids, grp, x[every], mm):
        if caps.get(g, 0) > 0:
            near[every[j]].append((g, d, i))
    lists = {t: [{g: i for g, d, i in near[p] if d <= t} for p in ps] for t, ps in guesses.items()}
    held = sum(len(ps) + sum(map(len, lists[t])) for t, ps in guesses.items())
    for t in sorted(guesses):
        adj = [sorted(e) for e in lists[t]]
        if saturates(adj, caps):
            return list(dict.fromkeys(e[g] for e, g in zip(lists[t], match_pivots(adj, caps)))), held
    raise ValueError("no guess matches: no point belongs to a group with capacity")


def prior_distributed_fair_centers(points: DataFrame, caps: Mapping[int, int], eps: float = 0.1, shards: int | None = None, m: Metric | str = "l1", how: str = "hash") -> DataFrame:
    """CENTER within 17 + eps in one round: workers send k pivots and the nearest member of each group around each; guesses are tried at the coordinator."""
    return prior_distributed_run(points, caps, eps, shards, m, how)[0]


def prior_distributed_run(points, caps, eps=0.1, shards=None, m="l1", how="hash") -> tuple[DataFrame, int]:
    """(CENTER, points that the workers send)."""
    caps, name, shards = check_caps(caps), metric(m).name, shards_for(points, shards)
    k = sum(caps.values())

    def run(shard, x, ids, grp):
        p, _, radius, _, _ = farthest_first(x, k, name)
        rows = []
        for i, at in enumerate(p):
            rows.append((shard, i, True, int(ids[at]), int(grp[at]), x[at].tolist()))
        rows += [(shard, i, False, int(ids[j]), g, x[j].tolist()) for i, g, d, j in nearest_by_group(x, ids, grp, x[p], name) if d <= radius]
        return pd.DataFrame(rows, columns=["shard", "place", "pivot", "point_id", "grp", "vec"]).astype({"place": "int32", "grp": "int32"})

    sent = to_driver(per_shard(shard_points(points, shards, how), run, "shard long, place int, pivot boolean, point_id long, grp int, vec array<double>")).sort_values(["shard", "place"], kind="stable")
    pivots, members = sent[sent["pivot"]], sent[~sent["pivot"]].drop_duplicates("point_id").sort_values("point_id")
    members = members[members.grp.map(lambda g: caps.get(g, 0) > 0)]
    x, y = np.stack(pivots.vec.to_numpy()).astype(float), np.stack(members.vec.to_numpy()).astype(float)
    mm = metric(name)
    d = mm.block(y, x)
    both = np.vstack([x, y])
    low = min((float(r[r > 0].min()) for r in (mm.one_to_many(v, both) for v in x) if (r > 0).any()), default=1.0)
    high = max(float(mm.block(x, x).max()), low)
    grp = members.grp.to_numpy()
    for t in guess_grid(low / 10, high, eps):
        kept = spread_subset(x, 10 * t, mm, k)
        if len(kept) > k:
            continue
        adj = [sorted(set(grp[d[:, i] <= 5 * t].tolist())) for i in kept]
        if saturates(adj, caps):
            rows = []
            for i, g in zip(kept, match_pivots(adj, caps)):
                mine = np.flatnonzero(grp == g)
                rows.append(int(mine[d[mine, i].argmin()]))
            got = members.iloc[list(dict.fromkeys(rows))]
            return centers_frame(points.sparkSession, got.point_id, got.grp, got.vec), sent.point_id.nunique()
    raise ValueError("no guess matches: no point belongs to a group with capacity")


def exact_fair_centers(points: DataFrame, caps: Mapping[int, int], m: Metric | str = "l1") -> DataFrame:
    """CENTER of least cost by brute force (a few dozen points)."""
    x, ids, grp = arrays(to_driver(points.select("point_id", "grp", "vec"), 60))
    rows = solve_exact(x, grp, check_caps(caps), m).rows
    return centers_frame(points.sparkSession, ids[rows], grp[rows], x[rows])


def random_fair_centers(points: DataFrame, caps: Mapping[int, int], seed: int = 3) -> DataFrame:
    """CENTER: per group the first ``cap`` points in hash order, picked per task before any exchange."""
    caps = check_caps(caps)
    spark = points.sparkSession
    table = F.broadcast(spark.createDataFrame([(g, c) for g, c in caps.items() if c > 0], "grp int, cap int"))
    rows = points.join(table, "grp").withColumn("h", F.md5(F.concat(F.lit(f"{seed}:"), F.col("point_id").cast("string")).cast("binary")))
    local = W.partitionBy("grp", F.substring("h", 1, 3)).orderBy("h", "point_id")
    rows = staged(rows.withColumn("r", F.row_number().over(local)).where("r <= cap"), "random-candidates")
    last = W.partitionBy("grp").orderBy("h", "point_id")
    kept = rows.withColumn("r", F.row_number().over(last)).where("r <= cap")
    return kept.select(F.row_number().over(W.orderBy("grp", "r")).alias("rank"), "point_id", "grp", "vec").withColumn("rank", F.col("rank") - 1)
