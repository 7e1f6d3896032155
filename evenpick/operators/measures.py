"""Cost, ratio, feasibility, aspect ratio, representation, sizes and times."""

from __future__ import annotations

import time
from collections.abc import Callable, Mapping, Sequence
from itertools import batched

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evenpick.functions.metrics import Metric, metric
from evenpick.operators.frames import BLOCK_VALUES, matrix, to_driver, vector_blocks
from evenpick.operators.greedy import farthest_first_rounds, with_distance
from evenpick.plans.durable import ship_package

MAX_CENTERS = 100_000


def center_vectors(centers: DataFrame) -> list[list[float]]:
    """Vectors of a center table in rank order; a center table is bounded by the capacities."""
    order = ["rank"] if "rank" in centers.columns else ["point_id"]
    return [list(v) for v in to_driver(centers.orderBy(*order).select("vec"), MAX_CENTERS).vec]


def cost(points: DataFrame, centers: DataFrame | list[list[float]], m: Metric | str = "l1") -> DataFrame:
    """One row ``cost``: the largest distance of a point to its nearest center (partial max per task, one scan)."""
    c = centers if isinstance(centers, list) else center_vectors(centers)
    return with_distance(points, c, m, "__d").agg(F.max("__d").alias("cost"))


def costs(points: DataFrame, centers: Sequence[list[list[float]]], m: Metric | str = "l1", rows: int = 2048) -> list[float]:
    """The cost of each of several center sets, all from one scan."""
    ship_package(points.sparkSession)
    sets, name = [np.array(c, float) for c in centers], metric(m).name

    def run(batches):
        most = np.full(len(sets), -np.inf)
        for b in batches:
            step = rows if pa.types.is_binary(b.schema.field(0).type) else max(1, min(rows, BLOCK_VALUES // max(1, len(sets[0][0]))))
            for i in range(0, b.num_rows, step):
                for _, x in vector_blocks(b.column(0).slice(i, step)):
                    most = np.maximum(most, [metric(name).block(x, c).min(1).max() for c in sets])
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(sets), dtype=np.int32)), pa.array(most)], names=["at", "cost"])

    got = points.select("vec").mapInArrow(run, "at int, cost double").groupBy("at").agg(F.max("cost")).collect()
    return [c for _, c in sorted(got)]


def cost_by_group(points: DataFrame, centers: DataFrame | list[list[float]], m: Metric | str = "l1") -> DataFrame:
    """Per group: cost, mean distance, and a profile of distances."""
    c = centers if isinstance(centers, list) else center_vectors(centers)
    d = with_distance(points, c, m, "__d")
    return d.groupBy("grp").agg(F.max("__d").alias("cost"), F.avg("__d").alias("mean_dist"), F.count("*").alias("points"))


def cost_bound(net: DataFrame, centers: DataFrame, covering: float, m: Metric | str = "l1") -> float:
    """A bound on the cost without touching the points: net cost plus twice the covering radius."""
    return float(cost(net, centers, m).first().cost) + 2 * covering


def opt_lower_bound(radii: DataFrame) -> DataFrame:
    """From greedy radii of any subsets (``radius``): half the largest bounds the optimum of the whole from below."""
    return radii.agg((F.max("radius") / 2).alias("lower_bound"))


def cost_ratio(points: DataFrame, centers: DataFrame, k: int, m: Metric | str = "l1") -> DataFrame:
    """(cost, greedy_radius, ratio_greedy, ratio_true): the greedy radius is the printed normaliser; the certified ratio uses half of it."""
    c = float(cost(points, centers, m).first().cost)
    _, g = farthest_first_rounds(points, k, m)
    return points.sparkSession.createDataFrame([(c, g, c / g if g else 1.0, 2 * c / g if g else 1.0)], "cost double, greedy_radius double, ratio_greedy double, ratio_true double")


def approx_ratio(points: DataFrame, centers: DataFrame, caps: Mapping[int, int], m: Metric | str = "l1") -> DataFrame:
    """(cost, optimum, ratio) on a set small enough for the exact solver."""
    from evenpick.operators.baselines import exact_fair_centers

    c, best = (float(cost(points, s, m).first().cost) for s in (centers, exact_fair_centers(points, caps, m)))
    return points.sparkSession.createDataFrame([(c, best, c / best if best else 1.0)], "cost double, optimum double, ratio double")


def feasibility(centers: DataFrame, caps: Mapping[int, int]) -> DataFrame:
    """Per group with a capacity: centers used, capacity, and whether they fit (groups without centers included)."""
    spark = centers.sparkSession
    table = spark.createDataFrame([(int(g), int(c)) for g, c in caps.items()], "grp int, cap int")
    used = centers.groupBy("grp").agg(F.count("*").alias("used"))
    return F.broadcast(table).join(used, "grp", "full_outer").select("grp", F.coalesce("used", F.lit(0)).cast("long").alias("used"), F.coalesce("cap", F.lit(0)).alias("cap")).withColumn("fits", F.col("used") <= F.col("cap"))


def representation(points: DataFrame, centers: DataFrame, caps: Mapping[int, int]) -> DataFrame:
    """Per group: share of points, of centers, and of capacity."""
    p = points.groupBy("grp").agg(F.count("*").alias("points"))
    f = feasibility(centers, caps)
    from pyspark.sql import Window as W

    all_ = W.partitionBy()
    joined = p.join(F.broadcast(f), "grp", "full_outer").select("grp", F.coalesce("points", F.lit(0)).alias("points"), F.coalesce("used", F.lit(0)).alias("used"), F.coalesce("cap", F.lit(0)).alias("cap"))
    return joined.select("grp", "points", "used", "cap", (F.col("points") / F.sum("points").over(all_)).alias("point_share"), (F.col("used") / F.sum("used").over(all_)).alias("center_share"), (F.col("cap") / F.sum("cap").over(all_)).alias("cap_share"))


#: Least and largest distance of two boxes from their gaps and reaches by coordinate; other metrics have no bound.
_OF_BOXES = {"l1": lambda d: d.sum(-1), "inversions": lambda d: d.sum(-1), "l2": lambda d: np.sqrt((d * d).sum(-1)), "linf": lambda d: d.max(-1)}


def _box_bounds(lo: np.ndarray, hi: np.ndarray, i: int, name: str) -> tuple[np.ndarray, np.ndarray]:
    """(at least, at most) of the distances between box ``i`` and every later box, wide enough for rounding."""
    a, b = lo[i + 1 :], hi[i + 1 :]
    if name not in _OF_BOXES:
        return np.zeros(len(a)), np.full(len(a), np.inf)
    slack = 1e-14 * (1 + lo.shape[1]) * max(np.abs(lo).max(), np.abs(hi).max())
    fold = _OF_BOXES[name]
    return fold(np.maximum(0, np.maximum(a - hi[i], lo[i] - b))) * (1 - 1e-12) - slack, fold(np.maximum(b - lo[i], hi[i] - a)) * (1 + 1e-12) + slack


def aspect_ratio(points: DataFrame, m: Metric | str = "l1", block: int = 2048) -> DataFrame:
    """(max_dist, min_dist, aspect_ratio) over all pairs, exactly; zero distances do not count.

    Distinct positions are sorted and cut into blocks of ``block`` rows. Pairs of blocks are compared unless their bounding boxes show that
    neither the least nor the largest distance can lie between them: about n * block work in few dimensions, n^2 where boxes tell nothing
    (many dimensions, metrics without bounds). There the greedy radius (``farthest_first_rounds``) is an estimate of the largest distance.
    """
    from evenpick.sources.points import dense_ids

    spark = points.sparkSession
    ship_package(spark)
    name = metric(m).name
    table = "max_dist double, min_dist double, aspect_ratio double"
    rows = dense_ids(points.groupBy("vec").agg(F.count("*").alias("copies")), ["vec"], "place").select("vec", "copies", F.floor(F.col("place") / block).cast("int").alias("b"))

    def extremes(a: np.ndarray, b: np.ndarray | None) -> tuple[float, float]:
        """The largest and the least positive distance between two blocks, or (None) inside one."""
        most, least = 0.0, np.inf
        for i in range(len(a)):
            d = metric(name).one_to_many(a[i], a[i + 1 :] if b is None else b)
            d = d[d > 0]
            if len(d):
                most, least = max(most, float(d.max())), min(least, float(d.min()))
        return most, least

    def own(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        x = matrix(pdf.vec.to_numpy())
        most, least = extremes(x, None)
        return pd.DataFrame({"b": [key[0]], "n": [int(pdf.copies.sum())], "lo": [x.min(0)], "hi": [x.max(0)], "most": [most], "least": [least]})

    boxes = rows.groupBy("b").applyInPandas(own, "b int, n long, lo array<double>, hi array<double>, most double, least double").toPandas().sort_values("b")
    if boxes.n.sum() < 2:
        return spark.createDataFrame([(None, None, None)], table)
    at, lo, hi = boxes.b.to_numpy(), matrix(boxes.lo.to_numpy()), matrix(boxes.hi.to_numpy())
    most, least = float(boxes.most.max()), float(boxes.least.min())

    def across(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        x, first = matrix(pdf.vec.to_numpy()), pdf.b.to_numpy() == key[0]
        got = extremes(x[first], x[~first])
        return pd.DataFrame({"most": [got[0]], "least": [got[1]]})

    def compared(pairs: Sequence[tuple[int, int]]) -> tuple[float, float]:
        if not pairs:
            return most, least
        sides = spark.createDataFrame(pd.DataFrame([(int(at[s]), int(at[i]), int(at[j])) for i, j in pairs for s in (i, j)], columns=["b", "i", "j"]), "b int, i int, j int")
        both = rows.join(F.broadcast(sides), "b").select("vec", "b", "i", "j").groupBy("i", "j").applyInPandas(across, "most double, least double")
        got = both.agg(F.max("most"), F.min("least")).first()
        return max(most, got[0]), min(least, got[1])

    def open_pairs(most: float, least: float):
        for i in range(len(at) - 1):
            low, high = _box_bounds(lo, hi, i, name)
            for j in np.flatnonzero(~((low > least) & (high < most))):
                yield i, i + 1 + int(j)

    near, far = [], []
    for i in range(len(at) - 1):
        low, high = _box_bounds(lo, hi, i, name)
        near.append((low.min(), i, i + 1 + int(low.argmin()))), far.append((-high.max(), i, i + 1 + int(high.argmax())))
    some = {(i, j) for _, i, j in [*sorted(near)[:32], *sorted(far)[:32]]}
    most, least = compared(sorted(some))
    for pairs in batched((p for p in open_pairs(most, least) if p not in some), 100_000):
        most, least = compared(pairs)
    return spark.createDataFrame([(most, least, most / least) if least < np.inf else (most, None, None)], table)


def doubling_dimension(points: DataFrame, radius: float, m: Metric | str = "l1") -> float:
    """Diagnostic: log2 of the growth of a threshold net when its radius halves."""
    import math

    from evenpick.operators.nets import threshold_net

    return math.log2(threshold_net(points, radius / 2, m).count() / threshold_net(points, radius, m).count())


def points_held(net: DataFrame) -> DataFrame:
    """Number of distinct points that a net keeps: net points and representatives."""
    ids = net.select(F.col("net_id").alias("id")).union(net.select(F.explode("reps.point_id")))
    return ids.agg(F.count_distinct("id").alias("points_held"))


def timed(run: Callable, repeats: int = 3) -> tuple[object, float]:
    """The last result and the mean seconds of ``repeats`` runs."""
    total, out = 0.0, None
    for _ in range(repeats):
        at = time.perf_counter()
        out = run()
        total += time.perf_counter() - at
    return out, total / repeats


def distance_profile(points: DataFrame, centers: DataFrame | list[list[float]], m: Metric | str = "l1", levels=(0.5, 0.9, 0.99)) -> DataFrame:
    """One row of exact percentiles of the distance to the nearest center, and its maximum (the cost)."""
    c = centers if isinstance(centers, list) else center_vectors(centers)
    d = with_distance(points, c, m, "__d")
    return d.agg(*[F.percentile("__d", F.lit(p)).alias(f"p{int(p * 100)}") for p in levels], F.max("__d").alias("cost"))


def points_sent(summaries: DataFrame) -> DataFrame:
    """What workers send: shards, net points, representatives, and the most of one shard."""
    per = summaries.groupBy("shard").agg(F.count("*").alias("n"), F.sum(F.size("reps")).alias("r"))
    return per.agg(F.count("*").alias("shards"), F.sum("n").alias("net_points"), F.sum("r").alias("representatives"), F.max("r").alias("most_of_a_shard"))
