"""Nets with group bits and representatives: from scratch, by assignment, merged, checked, expanded, solved on and lifted."""

from __future__ import annotations

from collections.abc import Callable, Mapping

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evenpick.functions import kernels
from evenpick.functions.kernels import Net
from evenpick.functions.metrics import Metric, metric
from evenpick.functions.solver import SOLVERS, Solution, check_caps
from evenpick.operators.frames import DRIVER_ROWS, MAX_GROUPS, NET, REPS, centers_frame, dense, in_order, matrix, net_of, net_rows, to_driver, whole_numbers
from evenpick.plans.durable import ship_package


def threshold_net(points: DataFrame, radius: float, m: Metric | str = "l1", order: str = "point_id", reps: str = "first") -> DataFrame:
    """NET of all points in one ordered pass: a point opens a net point unless an earlier one lies within ``radius``."""
    name = metric(m).name

    def run(blocks):
        net = Net()
        for x, ids, grp in blocks:
            net = kernels.extend_net(net, x, ids, grp, radius, name, reps)
        yield net_rows(net)

    return in_order(points, [order], run, NET)


def group_bit() -> Column:
    """The bit of a row's group (the shift's width comes from a column)."""
    return F.expr("shiftleft(1L, grp)")


def attach_groups(assignment: DataFrame, net: DataFrame, policy: str = "nearest", order: str = "point_id") -> DataFrame:
    """NET from an assignment ``(point_id, grp, vec, net_id, dist)`` and net points ``(net_id, vec, grp)``, by partial aggregation alone.

    'nearest' keeps the nearest member of each group, 'first' the first in ``order``; a net point represents its own group either way
    ('nearest') or before all others ('first').
    """
    key = F.struct("dist", "point_id") if policy == "nearest" else F.struct((F.col("point_id") != F.col("net_id")).alias("late"), F.col(order).alias("o"))
    rep = F.struct("grp", "point_id", "vec", "dist")
    per_group = assignment.groupBy("net_id", "grp").agg(F.min_by(rep, key).alias("rep"))
    bits = per_group.groupBy("net_id").agg(F.bit_or(group_bit()).alias("groups"), F.array_sort(F.collect_list("rep")).alias("reps"))
    return net.select("net_id", "vec", "grp").join(bits, "net_id").select("net_id", "vec", "grp", "groups", F.col("reps").cast(REPS).alias("reps"))


def check_net(net: DataFrame, points: DataFrame, radius: float, alpha: float, m: Metric | str = "l1", limit: int = 200_000) -> DataFrame:
    """One row: packing and covering of a net against its points.

    The net is a summary of at most ``limit`` rows; its own rows and the points are compared with it in tasks, block by block.
    """
    from evenpick.operators.greedy import with_distance

    x = matrix(to_driver(net.select("net_id", "vec").orderBy("net_id"), limit).vec.to_numpy())
    name = metric(m).name
    ship_package(net.sparkSession)

    def gaps(batches):
        for b in batches:
            y = matrix(b.vec.to_numpy())
            for i in range(0, len(y), 256):
                d = metric(name).block(y[i : i + 256], x)
                d[np.arange(len(d)), b.place.to_numpy()[i : i + 256]] = np.inf
                yield pd.DataFrame({"gap": d.min(1)})

    spark = net.sparkSession
    own = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "place long, vec array<double>")
    gap = own.repartition(max(1, len(x) // 2048)).mapInPandas(gaps, "gap double").agg(F.min("gap")).first()[0]
    gap = float("inf") if gap is None else gap
    cover = with_distance(points.select("point_id", "vec"), x.tolist(), m, "dist").agg(F.max("dist").alias("c"))
    return cover.select(
        F.lit(len(x)).cast("long").alias("net_points"),
        F.lit(gap).alias("least_gap"),
        F.col("c").alias("covering"),
        F.lit(gap >= radius).alias("packed"),
        (F.col("c") <= alpha * radius).alias("covered"),
    )


def is_proper(radius: float, alpha: float, eps: float, opt: float) -> bool:
    return radius <= eps / alpha * opt


def expand_labels(net: DataFrame, located: str = "center") -> DataFrame:
    """One labelled copy per net point and group present: ``(net_id, grp, vec, rep_id, rep_vec)``, at the net point or at the representative."""
    e = net.select("net_id", F.col("vec").alias("at"), F.explode("reps").alias("r"))
    vec = F.col("at") if located == "center" else F.col("r.vec")
    return e.select("net_id", F.col("r.grp").alias("grp"), vec.alias("vec"), F.col("r.point_id").alias("rep_id"), F.col("r.vec").alias("rep_vec"))


def is_candidate_feasible(chosen: DataFrame, net: DataFrame, caps: Mapping[int, int]) -> bool:
    """Whether net points ``(net_id)`` can be matched to groups present near them within the capacities."""
    from evenpick.functions.matching import saturates

    bits = [r.groups for r in chosen.select("net_id").distinct().join(net.select("net_id", "groups"), "net_id").collect()]
    return saturates([[g for g in range(MAX_GROUPS) if b >> g & 1] for b in bits], dict(caps))


def solve_arrays(x, ids, grp, caps, solver: str | Callable, m: Metric | str, fill: str) -> Solution:
    run = SOLVERS[solver] if isinstance(solver, str) else solver
    return run(x, grp, caps, m, fill=fill) if run is SOLVERS["static"] else run(x, grp, caps, m)


def solve_on_net(net: DataFrame, caps: Mapping[int, int], solver: str | Callable = "static", m: Metric | str = "l1", located: str = "center", fill: str = "none", keep_all: bool = False, lift: bool = True, limit: int = DRIVER_ROWS) -> DataFrame:
    """CENTER: any solver on the net's labelled copies, lifted to real points (or, without ``lift``, where the copies are).

    Up to ``limit`` copies the solver runs in the driver; more are solved by the static solver's distributed form, with the same result.
    ``keep_all`` keeps several copies of one net point.
    """
    caps = check_caps(caps)
    copies = expand_labels(net, located)
    if copies.limit(limit + 1).count() > limit:
        return _solve_large(copies, caps, solver, m, located, fill, keep_all, lift)
    if located == "rep":  # a representative crosses once, with one vector: wide ones would fill the driver
        one = F.min_by(F.struct("net_id", "grp", "vec"), F.struct("net_id", "grp"))
        copies = copies.groupBy("rep_id").agg(one.alias("one")).select("one.net_id", "one.grp", "one.vec", "rep_id")
    table = copies.toArrow()
    net_id, rep_id, grp = (whole_numbers(table[c]) for c in ("net_id", "rep_id", "grp"))
    order = np.lexsort((grp, net_id, rep_id))
    rows = order[solve_arrays(dense(table["vec"])[order], rep_id[order], grp[order], caps, solver, m, fill).rows]
    got = table.take(pa.array(rows)).to_pandas().assign(rank=range(len(rows)))
    return _lifted(net, got.assign(rep_vec=got.vec) if located == "rep" else got, located, keep_all, lift)


def _lifted(frame: DataFrame, got: pd.DataFrame, located: str, keep_all: bool, lift: bool) -> DataFrame:
    """CENTER from chosen copies in rank order: one per net point and one per representative."""
    got = got.sort_values("rank")
    if located == "center" and not keep_all:
        got = got.drop_duplicates("net_id")
    got = got.drop_duplicates("rep_id")
    return centers_frame(frame.sparkSession, got.rep_id, got.grp, got.rep_vec if lift else got.vec)


def _solve_large(copies: DataFrame, caps, solver, m, located: str, fill: str, keep_all: bool, lift: bool) -> DataFrame:
    from evenpick.operators.static import static_fair_centers
    from evenpick.sources.points import dense_ids

    if solver != "static":
        raise ValueError("more copies than the driver takes: only the static solver has a distributed form")
    if located == "rep":
        copies = copies.dropDuplicates(["rep_id"])
    rows = dense_ids(copies, ["rep_id", "net_id", "grp"])
    chosen = static_fair_centers(rows.select("point_id", "grp", "vec"), caps, m, fill, "rounds").select("rank", "point_id")
    return _lifted(copies, rows.join(F.broadcast(chosen), "point_id").toPandas(), located, keep_all, lift)


def merge_nets(fine: DataFrame, coarse: DataFrame | None, radius: float, m: Metric | str = "l1", alpha: float = 1.0, reps: str = "first") -> DataFrame:
    """NET: the finer net absorbed into the coarser one (None: empty) in order of net ids, as one group of a summary-sized table."""
    name = metric(m).name
    both = fine.withColumn("side", F.lit(0))
    if coarse is not None:
        both = both.unionByName(coarse.withColumn("side", F.lit(1)))
    ship_package(fine.sparkSession)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("net_id", kind="stable")
        return net_rows(kernels.merge_nets(net_of(pdf[pdf.side == 0]), net_of(pdf[pdf.side == 1]), radius, name, alpha, reps))

    return both.withColumn("bucket", F.lit(0)).groupBy("bucket").applyInPandas(run, NET)


def coreset_distortion(core: DataFrame, points: DataFrame, centers: DataFrame, m: Metric | str = "l1") -> DataFrame:
    """(core_cost, full_cost, distortion): how far the cost on a coreset ``(vec)`` is from the cost on all points."""
    from evenpick.operators.measures import cost

    a, b = cost(core, centers, m).first().cost, cost(points, centers, m).first().cost
    return points.sparkSession.createDataFrame([(float(a), float(b), abs(1 - a / b) if b else 0.0)], "core_cost double, full_cost double, distortion double")
