"""The static 3-approximation over all points: k + 1 scans as DataFrame rounds, or one driver run where the points fit."""

from __future__ import annotations

from collections.abc import Mapping

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evenpick.functions.kernels import nearest_by_group
from evenpick.functions.matching import match_pivots, saturates
from evenpick.functions.metrics import Metric, metric
from evenpick.functions.solver import check_caps, solve_static
from evenpick.operators.frames import arrow_schema, centers_frame, for_driver, point_arrays, vector_blocks, whole_numbers
from evenpick.operators.greedy import farthest_first_rounds, with_distance
from evenpick.plans.durable import ship_package

NEAR = "pivot int, grp int, dist double, point_id long, vec array<double>"


def static_fair_centers(points: DataFrame, caps: Mapping[int, int], m: Metric | str = "l1", fill: str = "none", where: str = "auto") -> DataFrame:
    """CENTER within 3 times the optimum. ``where``: 'driver', 'rounds', or 'auto' by the measured size; both give the same centers."""
    caps = check_caps(caps)
    if where == "auto":
        points, fits = for_driver(points)
        where = "driver" if fits else "rounds"
    if where == "driver":
        x, ids, grp = point_arrays(points)
        rows = solve_static(x, grp, caps, m, fill).rows
        return centers_frame(points.sparkSession, ids[rows], grp[rows], x[rows])
    return static_rounds(points, caps, m, fill)


def nearest_members(points: DataFrame, pivots: list[list[float]], m: Metric | str = "l1") -> DataFrame:
    """(pivot, grp, dist, point_id, vec): nearest member of each group for each pivot: every task keeps one row per pair, then they are reduced."""
    ship_package(points.sparkSession)
    c, name, out = np.array(pivots, float), metric(m).name, arrow_schema(NEAR)

    def run(batches):
        best: dict[tuple[int, int], tuple] = {}
        for b in batches:
            for at, x in vector_blocks(b.column(2)):
                ids = whole_numbers(b.column(0))[at]
                for j, g, d, i in nearest_by_group(x, ids, whole_numbers(b.column(1))[at], c, name) if len(x) else ():
                    if (j, g) not in best or (d, ids[i]) < best[j, g][:2]:
                        best[j, g] = (d, int(ids[i]), x[i].tolist())
        pdf = pd.DataFrame([(j, g, *v) for (j, g), v in best.items()], columns=["pivot", "grp", "dist", "point_id", "vec"])
        yield from pa.Table.from_pandas(pdf, out, preserve_index=False).to_batches()

    near = points.select("point_id", "grp", "vec").mapInArrow(run, NEAR)
    best = near.groupBy("pivot", "grp").agg(F.min_by(F.struct("dist", "point_id", "vec"), F.struct("dist", "point_id")).alias("b"))
    return best.select("pivot", "grp", "b.dist", "b.point_id", "b.vec")


def fill_rounds(points: DataFrame, caps: Mapping[int, int], chosen: list, m: Metric | str = "l1") -> list:
    """Rows (point_id, grp, vec) that spend spare capacity on the farthest points of groups with room: one scan each, ties to the smaller id."""
    left = {g: c - sum(1 for r in chosen if r.grp == g) for g, c in caps.items()}
    more: list = []
    while room := [g for g, c in left.items() if c > 0]:
        far = with_distance(points.select("point_id", "grp", "vec").where(F.col("grp").isin(room)), [list(r.vec) for r in [*chosen, *more]], m, "md").where("md > 0")
        p = far.agg(F.max_by(F.struct("point_id", "grp", "vec"), F.struct(F.col("md"), -F.col("point_id"))).alias("p")).first().p
        if p is None:
            break
        more.append(p)
        left[p.grp] -= 1
    return more


def static_rounds(points: DataFrame, caps: Mapping[int, int], m: Metric | str = "l1", fill: str = "none") -> DataFrame:
    """The same solution from frames: greedy rounds, one scan for the nearest members, matching over k times m numbers."""
    pivots, _ = farthest_first_rounds(points, sum(caps.values()), m)
    delta = [d for *_, d in pivots]
    table = {(r.pivot, r.grp): r for r in nearest_members(points.where(F.col("grp").isin([g for g, c in caps.items() if c > 0])), [v for _, v, _ in pivots], m).collect()}
    groups = sorted(g for g, c in caps.items() if c > 0)
    lists = lambda h, ok: [[g for g in groups if (i, g) in table and ok(table[i, g].dist)] for i in range(h)]
    passes = lambda h: saturates(lists(h, lambda d: d < delta[h - 1] / 2), caps)
    low, high = 1, len(pivots)
    while low < high:
        mid = (low + high + 1) // 2
        low, high = (mid, high) if passes(mid) else (low, mid - 1)
    radii = sorted({table[i, g].dist for i in range(low) for g in groups if (i, g) in table and table[i, g].dist < delta[low - 1] / 2})
    rho = next(r for r in radii if saturates(lists(low, lambda d: d <= r), caps))
    chosen = [table[i, g] for i, g in enumerate(match_pivots(lists(low, lambda d: d <= rho), caps))]
    if fill == "greedy":
        chosen += fill_rounds(points, caps, chosen, m)
    return centers_frame(points.sparkSession, [c.point_id for c in chosen], [c.grp for c in chosen], [c.vec for c in chosen])
