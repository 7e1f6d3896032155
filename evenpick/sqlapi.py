"""SQL surface: distances as functions, and table functions over partitioned tables."""

from __future__ import annotations

import json

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

from evenpick.functions.kernels import BudgetNet, Net, threshold_net
from evenpick.functions.solver import solve_static
from evenpick.plans.durable import ship_package


def _total(term: str) -> str:
    return f"aggregate(zip_with(a, b, (x, y) -> {term}), 0D, (s, t) -> s + t)"


def _angle() -> str:
    norm = f"{_total('x * x')} * {_total('y * y')}"
    return f"acos(greatest(-1D, least(1D, CASE WHEN {norm} > 0 THEN {_total('x * y')} / sqrt({norm}) ELSE 0D END))) / pi()"


#: The metrics as SQL over arrays a and b, evaluated in the JVM.
DISTANCES = {
    "l1": _total("abs(x - y)"),
    "inversions": _total("abs(x - y)"),
    "l2": f"sqrt({_total('(x - y) * (x - y)')})",
    "linf": "array_max(zip_with(a, b, (x, y) -> abs(x - y)))",
    "hamming": _total("CAST(x != y AS DOUBLE)"),
    "jaccard": f"coalesce(1 - {_total('CAST(x != 0 AND y != 0 AS DOUBLE)')} / nullif({_total('CAST(x != 0 OR y != 0 AS DOUBLE)')}, 0D), 0D)",
    "angular": _angle(),
}
MEMBERS = "array<struct<net_id: bigint, grp: int, point_id: bigint, vec: array<double>, dist: double>>"


def net_agg(radius: float, m: str = "l1"):
    """Grouped aggregate over ``(point_id, grp, vec)``: the representatives of a threshold net of each group of rows, taken in order of id.

    Unlike ``net_summary`` it holds its group's rows, so it is for groups that fit a task; the net operators take the others.
    """

    def run(ids: pd.Series, grp: pd.Series, vec: pd.Series) -> list:
        order = np.argsort(ids.to_numpy(), kind="stable")
        net = threshold_net(np.stack(vec.to_numpy()[order]).astype(float), ids.to_numpy()[order], grp.to_numpy()[order], radius, m) if len(ids) else Net()
        return [{"net_id": int(i), "grp": g, "point_id": p, "vec": x.tolist(), "dist": d} for i, reps in zip(net.ids, net.reps) for g, (p, x, d) in sorted(reps.items())]

    return pandas_udf(run, MEMBERS)


@udtf(returnType="net_id bigint, at array<double>, member_grp int, member_id bigint, member array<double>, dist double")
class NetSummary:
    """``net_summary(TABLE(points) PARTITION BY (shard) ORDER BY (point_id), budget)``: representatives of a budget net of each partition."""

    def __init__(self):
        self.rows, self.budget = [], 240

    def eval(self, row, budget: int):
        self.rows.append((row["point_id"], row["grp"], row["vec"]))
        self.budget = budget
        if len(self.rows) >= 4096:
            self._flush()

    def _flush(self):
        if not hasattr(self, "net"):
            self.net = BudgetNet(self.budget)
        if self.rows:
            ids, grp, vec = zip(*self.rows)
            self.net.insert_block(np.array(vec, float), np.array(ids), np.array(grp))
            self.rows = []

    def terminate(self):
        self._flush()
        for i, v, reps in zip(self.net.net.ids, self.net.net.vecs, self.net.net.reps):
            for g, (p, x, d) in sorted(reps.items()):
                yield i, v.tolist(), g, p, x.tolist(), d


@udtf(returnType="rank int, point_id bigint, grp int, vec array<double>")
class FairCentersTable:
    """``fair_centers(TABLE(members) WITH SINGLE PARTITION, '{"0": 2, "1": 2}')`` over rows ``(member_id, member_grp, member)``."""

    def __init__(self):
        self.seen, self.caps = {}, "{}"

    def eval(self, row, caps: str):
        self.seen[row["member_id"]] = (row["member_grp"], row["member"])
        self.caps = caps

    def terminate(self):
        ids = sorted(self.seen)
        if ids:
            x, grp = np.array([self.seen[i][1] for i in ids], float), np.array([self.seen[i][0] for i in ids])
            for k, r in enumerate(solve_static(x, grp, {int(g): c for g, c in json.loads(self.caps).items()}).rows):
                yield k, ids[r], int(grp[r]), x[r].tolist()


def register_sql(spark: SparkSession) -> None:
    """Register ``<metric>_distance`` functions and the two table functions."""
    ship_package(spark)
    for name, body in DISTANCES.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}_distance(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN {body}")
    spark.udtf.register("net_summary", NetSummary)
    spark.udtf.register("fair_centers", FairCentersTable)
