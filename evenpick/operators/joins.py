"""Assignments and ball joins around centers."""

from __future__ import annotations

from itertools import product

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evenpick.functions.metrics import UNROLL_TERMS, Metric, metric
from evenpick.operators.greedy import with_distance
from evenpick.operators.measures import center_vectors
from evenpick.plans.durable import ship_package


def assign_nearest(points: DataFrame, centers: DataFrame | list[list[float]], m: Metric | str = "l1") -> DataFrame:
    """``points`` with ``center`` (index in rank order, first on ties) and ``dist``. A pipeline of one scan, no exchange."""
    c = centers if isinstance(centers, list) else center_vectors(centers)
    return with_distance(points, c, m, "dist", "center")


def within(points: DataFrame, centers: DataFrame | list[list[float]], radius: float, m: Metric | str = "l1") -> DataFrame:
    """Points at most ``radius`` from a center."""
    return assign_nearest(points, centers, m).where(F.col("dist") <= radius)


def uncovered(points: DataFrame, centers: DataFrame | list[list[float]], radius: float, m: Metric | str = "l1") -> DataFrame:
    """Points farther than ``radius`` from every center."""
    return assign_nearest(points, centers, m).where(F.col("dist") > radius)


def ball_join(points: DataFrame, centers: DataFrame, radius: float, dims: int, m: Metric | str = "l1") -> DataFrame:
    """(point_id, center_id, dist) of all pairs at most ``radius`` apart, for few dimensions.

    Both sides are cut into cells of side ``radius``; centers are put into the 3^dims cells around them, so the join is an
    equi-join on cells (dealt and skew-split by the planner) with an exact filter. No cross join.
    """
    cell = lambda c: F.array(*[F.floor(F.get(c, i) / radius) for i in range(dims)])
    steps = F.array(*[F.array(*[F.lit(s).cast("long") for s in step]) for step in product((-1, 0, 1), repeat=dims)])
    right = centers.select(F.col("point_id").alias("center_id"), F.col("vec").alias("center_vec"), cell("vec").alias("home"))
    right = right.withColumn("step", F.explode(steps)).select("center_id", "center_vec", F.zip_with("home", "step", lambda a, b: a + b).alias("cell"))
    pairs = points.select("point_id", "vec", cell("vec").alias("cell")).join(right, "cell")
    return pairs.select("point_id", "center_id", metric(m).between(F.col("vec"), F.col("center_vec")).alias("dist")).where(F.col("dist") <= radius)


def in_force(reports: DataFrame, versions: DataFrame, at: str = "n_seen") -> DataFrame:
    """As-of join: each report row with the latest version row at or before it (union, then last known value)."""
    from pyspark.sql import Window as W

    keys = [c for c in versions.columns if c != at]
    a = reports.select(at, F.lit(1).alias("__r"), *[F.lit(None).cast(versions.schema[c].dataType).alias(c) for c in keys])
    b = versions.select(at, F.lit(0).alias("__r"), *keys)
    w = W.orderBy(at, "__r").rowsBetween(W.unboundedPreceding, 0)
    return a.unionByName(b).select(at, "__r", *[F.last(c, ignorenulls=True).over(w).alias(c) for c in keys]).where("__r = 1").drop("__r")


def nearest_centers(points: DataFrame, centers: DataFrame | list[list[float]], j: int, m: Metric | str = "l1") -> DataFrame:
    """(point_id, place, center, dist): each point's ``j`` nearest centers, ties to the earlier center. One scan, rows expanded in place."""
    c = centers if isinstance(centers, list) else center_vectors(centers)
    m = metric(m)
    if sum(map(len, c)) > UNROLL_TERMS:
        return _nearest_by_block(points, c, j, m.name)
    each = F.array(*[F.struct(m.to_point(F.col("vec"), v).alias("dist"), F.lit(i).alias("center")) for i, v in enumerate(c)])
    top = F.slice(F.array_sort(each), 1, j)
    return points.select("point_id", F.posexplode(top).alias("place", "c")).select("point_id", "place", "c.center", "c.dist")


def _nearest_by_block(points: DataFrame, c: list[list[float]], j: int, name: str) -> DataFrame:
    ship_package(points.sparkSession)
    centers = np.array(c, float)

    def run(batches):
        for b in batches:
            if not len(b):
                continue
            x, ids = np.stack(b.vec.to_numpy()).astype(float), b.point_id.to_numpy()
            for i in range(0, len(x), 1024):
                d = metric(name).block(x[i : i + 1024], centers)
                at = np.argsort(d, axis=1, kind="stable")[:, :j]
                place = np.broadcast_to(np.arange(at.shape[1]), at.shape)
                yield pd.DataFrame({"point_id": np.repeat(ids[i : i + 1024], at.shape[1]), "place": place.ravel().astype(np.int32), "center": at.ravel().astype(np.int32), "dist": np.take_along_axis(d, at, 1).ravel()})

    return points.select("point_id", "vec").mapInPandas(run, "point_id long, place int, center int, dist double")


def farthest_points(points: DataFrame, centers: DataFrame | list[list[float]], n: int, m: Metric | str = "l1") -> DataFrame:
    """The ``n`` points farthest from their nearest center (a top-n report; each task keeps n rows)."""
    return assign_nearest(points, centers, m).orderBy(F.col("dist").desc(), "point_id").limit(n).select("point_id", "center", "dist")


def within_interval(rows: DataFrame, at: str, intervals: DataFrame, start: str, stop: str, cell: int = 86_400) -> DataFrame:
    """``rows`` with every interval [start, stop) that holds ``at``: an equi-join on time cells of ``cell`` seconds, then the exact condition."""
    slot = lambda c: F.floor(F.unix_timestamp(c) / cell)
    right = intervals.withColumn("__cell", F.explode(F.sequence(slot(start), slot(stop))))
    return rows.withColumn("__cell", slot(at)).join(right, "__cell").where((F.col(at) >= F.col(start)) & (F.col(at) < F.col(stop))).drop("__cell")


def solution_overlap(a: DataFrame, b: DataFrame) -> DataFrame:
    """(point_id, grp, shared): the centers of ``a``, and whether ``b`` has them."""
    a, b = (c.select("point_id", "grp") for c in (a, b))
    return a.intersect(b).withColumn("shared", F.lit(True)).unionByName(a.exceptAll(b).withColumn("shared", F.lit(False)))


def partition_check(points: DataFrame, shards: DataFrame) -> DataFrame:
    """One row: whether ``shards`` (with ``point_id``) hold exactly the points, each once."""
    twice = shards.groupBy("point_id").count().where("count > 1").agg(F.count("*").alias("twice"))
    lost = points.join(shards, "point_id", "left_anti").agg(F.count("*").alias("lost"))
    extra = shards.join(points, "point_id", "left_anti").agg(F.count("*").alias("extra"))
    return twice.crossJoin(lost).crossJoin(extra)
