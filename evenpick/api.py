"""The estimator: one object for every method, and the model it fits."""

from __future__ import annotations

from collections.abc import Mapping
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from evenpick.operators import baselines, distributed, joins, measures, onepass, report
from evenpick.operators.frames import CENTER
from evenpick.operators.static import static_fair_centers

METHODS = ("distributed", "distributed_budget", "one_pass", "one_pass_budget", "sharded", "static", "two_pass", "prior_distributed", "exact", "random")
#: Methods that can spend spare capacity (``fill``).
FILLING = ("distributed", "distributed_budget", "one_pass_budget", "static")


@dataclass(frozen=True)
class FairCenters:
    """Fair center selection on points ``(point_id, grp, vec)`` with at most ``caps[g]`` centers of group g."""

    caps: Mapping[int, int]
    metric: str = "l1"
    method: str = "distributed_budget"
    eps: float | None = None
    budget: int | None = None
    shards: int | None = None
    how: str = "hash"
    solver: str = "static"
    fill: str = "none"

    def fit(self, points: DataFrame) -> FairCentersModel:
        c, m, s = self.caps, self.metric, self.shards
        runs = {
            "distributed": lambda: distributed.distributed_fair_centers(points, c, self.eps or 1.0, s, m, self.how, self.solver, fill=self.fill),
            "distributed_budget": lambda: distributed.distributed_fair_centers_budget(points, c, self.budget or 24, s, m, self.how, solver=self.solver, fill=self.fill),
            "one_pass": lambda: onepass.one_pass_fair_centers(points, c, self.eps or 1.0, m, solver=self.solver),
            "one_pass_budget": lambda: onepass.one_pass_fair_centers_budget(points, c, self.budget or 240, m, solver=self.solver, fill=self.fill),
            "sharded": lambda: onepass.sharded_fair_centers(points, c, self.eps or 1.0, s, m, self.how, self.solver),
            "static": lambda: static_fair_centers(points, c, m, self.fill),
            "two_pass": lambda: baselines.two_pass_fair_centers(points, c, self.eps or 0.1, m),
            "prior_distributed": lambda: baselines.prior_distributed_fair_centers(points, c, self.eps or 0.1, s, m, self.how),
            "exact": lambda: baselines.exact_fair_centers(points, c, m),
            "random": lambda: baselines.random_fair_centers(points, c),
        }
        if self.method not in runs:
            raise ValueError(f"method must be one of {METHODS}")
        if self.fill != "none" and self.method not in FILLING:
            raise ValueError(f"fill={self.fill!r} needs one of the methods {FILLING}")
        return FairCentersModel(self, runs[self.method]())


@dataclass(frozen=True)
class FairCentersModel:
    settings: FairCenters
    centers: DataFrame

    def cost(self, points: DataFrame) -> DataFrame:
        return measures.cost(points, self.centers, self.settings.metric)

    def assign(self, points: DataFrame) -> DataFrame:
        return joins.assign_nearest(points, self.centers, self.settings.metric)

    def feasibility(self) -> DataFrame:
        return measures.feasibility(self.centers, self.settings.caps)

    def representation(self, points: DataFrame) -> DataFrame:
        return measures.representation(points, self.centers, self.settings.caps)

    def save(self, path: str, mode: str = "error") -> None:
        self.centers.write.mode(mode).parquet(path)

    @staticmethod
    def load(spark: SparkSession, path: str, settings: FairCenters) -> FairCentersModel:
        return FairCentersModel(settings, spark.read.schema(CENTER).parquet(path))


def compare(points: DataFrame, caps: Mapping[int, int], methods=report.METHODS, **kw) -> DataFrame:
    """A table of methods with time, memory in points, cost and ratio."""
    return report.compare(points, caps, methods, **kw)
