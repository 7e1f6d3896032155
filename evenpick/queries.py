"""One query per method, variant, baseline, measure and workload."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenpick.functions.kernels import farthest_first
from evenpick.functions.matching import hall_feasible
from evenpick.functions.metrics import metric
from evenpick.functions.solver import nearest_members, solve_static
from evenpick.operators import baselines, distributed, joins, measures, nets, onepass, report, static
from evenpick.operators.frames import arrays, centers_frame, to_driver
from evenpick.operators.greedy import distance_evaluations, farthest_first_per_shard, farthest_first_rounds, greedy_pivots, with_distance
from evenpick.plans.durable import shared_dir, staged
from evenpick.sources import points as src
from evenpick.sqlapi import net_agg, register_sql
from evenpick.streaming import stream

Query = Callable[[SparkSession, str], DataFrame]
FIVE_TWO, FIVE_TEN, TWO_TEN = dict.fromkeys(range(5), 2), dict.fromkeys(range(5), 10), dict.fromkeys(range(2), 10)
#: Capacities of the set whose groups follow a feature.
SKEWED = {0: 1, 1: 9, 2: 9, 3: 1}
QUERIES: dict[str, Query] = {}


def query(run: Query) -> Query:
    QUERIES[run.__name__] = run
    return run


def rounded(df: DataFrame, digits: int = 6, *names: str) -> DataFrame:
    return df.withColumns({c: F.round(c, digits) for c in names})


def anchors(points: DataFrame) -> list[list[float]]:
    """The first point of each group, in group order (one row per group)."""
    rows = points.groupBy("grp").agg(F.min_by("vec", "point_id").alias("v")).orderBy("grp").collect()
    return [list(r.v) for r in rows]


def solved(points: DataFrame, centers: DataFrame, k: int, m: str = "l1") -> DataFrame:
    """What end-to-end queries return: the centers, their cost on all points, and its ratio to the greedy radius of ``k`` centers."""
    centers = staged(centers, "centers")
    c, g = float(measures.cost(points, centers, m).first().cost), greedy_pivots(points, k, m)[1]
    return centers.select("rank", "point_id", "grp", F.round(F.lit(c), 6).alias("cost"), F.round(F.lit(c / g), 6).alias("ratio"))


@query
def group_caps(spark, d):
    c = src.with_group(src.load(spark, d, "customer").select("c_mktsegment").distinct(), "c_mktsegment")
    return c.select(F.col("grp").cast("int"), F.col("c_mktsegment").alias("name"), F.lit(10).alias("cap"))


@query
def crossed_groups_rollup(spark, d):
    l, o = src.load(spark, d, "lineitem").select("l_orderkey", "l_linestatus"), src.load(spark, d, "orders").select("o_orderkey", "o_orderpriority")
    return l.join(o, l.l_orderkey == o.o_orderkey).rollup("l_linestatus", "o_orderpriority").agg(F.count("*").alias("points"))


@query
def crossed_groups_cube(spark, d):
    l, o = src.load(spark, d, "lineitem").select("l_orderkey", "l_linestatus"), src.load(spark, d, "orders").select("o_orderkey", "o_orderpriority")
    return l.join(o, l.l_orderkey == o.o_orderkey).cube("l_linestatus", "o_orderpriority").agg(F.count("*").alias("points"))


@query
def distinct_rankings(spark, d):
    """Points of chosen groups without copies inside a group."""
    pts = src.select_groups(src.user_rankings(spark, d), [0, 2, 4])
    return src.dedupe_points(pts).select("point_id", "grp")


@query
def solution_overlap(spark, d):
    """Centers that two methods share, and those that only the first has."""
    pts = staged(src.corr4(spark, d), "points")
    a, b = static.static_fair_centers(pts, SKEWED), baselines.two_pass_fair_centers(pts, SKEWED, 0.1)
    return joins.solution_overlap(a, b)


@query
def events_in_summaries(spark, d):
    """Interval join: events inside the validity of two-day summaries, per summary."""
    e = src.load(spark, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    day = F.date_trunc("day", "ts")
    valid = e.select(day.alias("start")).distinct().select("start", (F.col("start") + F.expr("INTERVAL 36 HOURS")).alias("stop"))
    return joins.within_interval(e, "ts", valid, "start", "stop").groupBy(src.day_number("start").alias("start_day")).agg(F.count("*").alias("events"))


@query
def points_w1_rankings(spark, d):
    return src.brand_positions(spark, d)


@query
def points_w2_scores(spark, d):
    total = F.aggregate("vec", F.lit(0.0), lambda a, x: a + x)
    weighted = F.aggregate(F.transform("vec", lambda x, i: x * (i + 1)), F.lit(0.0), lambda a, x: a + x)
    return src.score50(spark, d).select("point_id", total.cast("long").alias("total"), weighted.cast("long").alias("weighted"))


@query
def points_w3_normalised(spark, d):
    return src.line6(spark, d).select("point_id", "grp", *[(F.round(F.get("vec", i), 4) + 0.0).alias(f"z{i}") for i in range(6)])


@query
def metric_profile(spark, d):
    pts = src.cust2d(spark, d)
    c, out = anchors(pts), []
    for name in ("l1", "l2", "linf", "hamming"):
        for i, a in enumerate(c):
            out.append(F.struct(F.lit(name).alias("metric"), F.lit(i).alias("anchor"), F.round(F.max(metric(name).to_point(F.col("vec"), a)), 6).alias("most"), F.round(F.avg(metric(name).to_point(F.col("vec"), a)), 6).alias("mean")))
    return pts.agg(F.array(*out).alias("a")).select(F.inline("a"))


@query
def inversion_profile(spark, d):
    pts = src.rank10(spark, d)
    first = pts.orderBy("point_id").first()
    return pts.select("point_id", metric("inversions").to_point(F.col("vec"), first.vec).cast("long").alias("inversions"))


@query
def set_metric_profile(spark, d):
    """Jaccard and angular distances of all score vectors to the first."""
    pts = src.score50(spark, d)
    first = pts.orderBy("point_id").first().vec
    return pts.agg(*[F.round(f(metric(m).to_point(F.col("vec"), first)), 6).alias(f"{m}_{n}") for m in ("jaccard", "angular") for n, f in (("max", F.max), ("avg", F.avg))])


@query
def aspect_ratio_embeddings(spark, d):
    r = measures.aspect_ratio(src.emb64(spark, d))
    return rounded(r, 6, "max_dist", "min_dist", "aspect_ratio")


@query
def aspect_ratio_customer(spark, d):
    r = measures.aspect_ratio(src.cust2d(spark, d))
    return rounded(rounded(r, 6, "max_dist", "min_dist"), 3, "aspect_ratio")


def _pivots(spark, pivots, radius, digits):
    rows = [(i, p, 0.0 if i == 0 else float(delta), float(radius)) for i, (p, _, delta) in enumerate(pivots)]
    return rounded(spark.createDataFrame(rows, "rank int, point_id long, delta double, radius double"), digits, "delta", "radius")


@query
def farthest_first_customer(spark, d):
    return _pivots(spark, *farthest_first_rounds(src.cust2d(spark, d), 12), 6)


@query
def farthest_first_lineitem(spark, d):
    return _pivots(spark, *farthest_first_rounds(staged(src.line6(spark, d), "line6"), 8), 4)


@query
def farthest_first_shards(spark, d):
    out = farthest_first_per_shard(src.cust2d(spark, d), 5, 4, how="modulo")
    return rounded(out.withColumn("delta", F.when(F.col("rank") == 0, 0.0).otherwise(F.col("delta"))), 6, "delta", "radius")


QUERIES["farthest_first_per_shard"] = QUERIES.pop("farthest_first_shards")


@query
def lower_bound_radius(spark, d):
    radii = farthest_first_per_shard(src.cust2d(spark, d), 10, 4, how="modulo")
    return rounded(measures.opt_lower_bound(radii), 6, "lower_bound")


def _net1(spark, d, reps="first"):
    return nets.threshold_net(src.cust2d(spark, d), 1.0, reps=reps)


@query
def threshold_net_customer(spark, d):
    net = staged(_net1(spark, d), "net")
    pdf = to_driver(net.select("net_id", "vec"))
    ids = {i: n for i, n in enumerate(pdf.net_id)}
    pts = src.cust2d(spark, d)
    near = joins.ball_join(pts, net.select(F.col("net_id").alias("point_id"), "vec"), 1.0, 2)
    place = spark.createDataFrame([(int(n), i) for i, n in ids.items()], "center_id long, pos int")
    first = near.join(F.broadcast(place), "center_id").groupBy("point_id").agg(F.min_by("center_id", "pos").alias("net_id"))
    return net.select("net_id", "groups").join(first.groupBy("net_id").agg(F.count("*").alias("members")), "net_id")


@query
def net_representatives_first(spark, d):
    return _net1(spark, d).select("net_id", F.explode("reps").alias("r")).select("net_id", "r.grp", F.col("r.point_id").alias("rep_id"))


@query
def net_representatives_nearest(spark, d):
    return _net1(spark, d, "nearest").select("net_id", F.explode("reps").alias("r")).select("net_id", "r.grp", F.col("r.point_id").alias("rep_id"))


@query
def net_packing_covering(spark, d):
    return rounded(nets.check_net(staged(_net1(spark, d), "net"), src.cust2d(spark, d), 1.0, 1.0), 6, "least_gap", "covering")


@query
def net_groups_by_assignment(spark, d):
    """Group bits and nearest representatives of the first point of each segment, from an assignment by aggregation."""
    pts = src.cust2d(spark, d)
    firsts = pts.groupBy("grp").agg(F.min_by(F.struct("point_id", "vec", "grp"), "point_id").alias("p")).select("p.*").orderBy("grp")
    rows = firsts.collect()
    ids = F.array(*[F.lit(r.point_id) for r in rows])
    a = joins.assign_nearest(pts, [list(r.vec) for r in rows]).withColumn("net_id", F.get(ids, F.col("center")))
    net = nets.attach_groups(a, firsts.withColumnRenamed("point_id", "net_id"))
    return net.select("net_id", "groups", F.size("reps").alias("n_reps"), F.array_join(F.transform("reps", lambda r: r["point_id"].cast("string")), ",").alias("rep_ids"))


@query
def merge_nets_two_shards(spark, d):
    pts = src.cust2d(spark, d)
    fine = nets.threshold_net(pts.where("point_id % 2 = 0"), 0.5)
    coarse = nets.threshold_net(pts.where("point_id % 2 = 1"), 1.0)
    return nets.merge_nets(fine, coarse, 1.0).select("net_id", "groups")


@query
def worker_nets(spark, d):
    s = distributed.worker_net(src.cust2d(spark, d), 10, 1 / 3, 4, how="modulo")
    return s.groupBy("shard").agg(F.round(F.max("r_t"), 6).alias("r_t"), F.count("*").alias("net_points"), F.sum("net_id").alias("id_sum"))


@query
def coordinator_net(spark, d):
    s = staged(distributed.worker_net(src.cust2d(spark, d), 10, 1 / 3, 4, how="modulo"), "worker-nets")
    return distributed.coordinator_net(s, 1 / 3).select("net_id", "groups")


def _prefixes(spark, d):
    x, ids, grp = arrays(to_driver(src.cust2d(spark, d)))
    pivots, delta, _, _, _ = farthest_first(x, 10)
    dist, _ = nearest_members(x, grp, pivots, range(5), metric("l1"))
    masks = lambda h: [sum(1 << g for g in range(5) if dist[i, g] < delta[h - 1] / 2) for i in range(h)]
    return x, grp, {h: masks(h) for h in range(1, len(pivots) + 1)}


@query
def hall_feasible_prefixes(spark, d):
    _, _, masks = _prefixes(spark, d)
    return spark.createDataFrame([(h, sum(m), hall_feasible(m, FIVE_TWO)) for h, m in masks.items()], "prefix int, mask_sum long, feasible boolean")


@query
def static_prefix_and_radius(spark, d):
    x, _, grp = arrays(to_driver(src.cust2d(spark, d)))
    s = solve_static(x, grp, FIVE_TWO)
    return rounded(spark.createDataFrame([(s.prefix, s.radius)], "prefix int, radius double"), 6, "radius")


@query
def exact_fair_nations(spark, d):
    pts = src.nation_points(spark, d)
    c = baselines.exact_fair_centers(pts, dict.fromkeys(range(5), 1))
    return measures.cost(pts, c).select(F.round("cost", 6).alias("optimum"))


@query
def bounds_on_nations(spark, d):
    """Every method on the 25 nations: its centers, its cost, the ratio to the exact optimum, and whether that is within the method's factor."""
    pts, caps = staged(src.nation_points(spark, d), "nations"), dict.fromkeys(range(5), 1)
    runs = {
        "static": (3, lambda: static.static_fair_centers(pts, caps)),
        "two_pass": (3.1, lambda: baselines.two_pass_fair_centers(pts, caps, 0.1)),
        "prior_distributed": (17.1, lambda: baselines.prior_distributed_fair_centers(pts, caps, 0.1, 3, how="modulo")),
        "distributed": (6, lambda: distributed.distributed_fair_centers(pts, caps, 1.0, 3, how="modulo")),
        "distributed_budget": (3, lambda: distributed.distributed_fair_centers_budget(pts, caps, 25, 3, how="modulo")),
        "one_pass": (6, lambda: onepass.one_pass_fair_centers(pts, caps, 1.0)),
        "one_pass_budget": (3, lambda: onepass.one_pass_fair_centers_budget(pts, caps, 25)),
        "sharded": (6, lambda: onepass.sharded_fair_centers(pts, caps, 1.0, 3, how="modulo")),
    }
    rows = []
    for name, (factor, run) in runs.items():
        c = run().orderBy("rank")
        r = measures.approx_ratio(pts, c, caps).first()
        rows.append((name, ",".join(str(x.point_id) for x in c.collect()), r.cost, r.ratio, r.cost <= factor * r.optimum))
    out = spark.createDataFrame(rows, "method string, centers string, cost double, ratio_to_optimum double, within_factor boolean")
    return rounded(out, 6, "cost", "ratio_to_optimum")


@query
def cost_fixed_centers(spark, d):
    pts = src.cust2d(spark, d)
    return rounded(measures.cost(pts, anchors(pts)), 6, "cost")


@query
def cost_by_group(spark, d):
    pts = src.cust2d(spark, d)
    return rounded(measures.cost_by_group(pts, anchors(pts)), 6, "cost", "mean_dist")


@query
def assign_nearest(spark, d):
    pts = src.cust2d(spark, d)
    return rounded(joins.assign_nearest(pts, anchors(pts)).select("point_id", "center", "dist"), 6, "dist")


@query
def uncovered_points(spark, d):
    pts = src.cust2d(spark, d)
    return rounded(joins.uncovered(pts, anchors(pts), 3.0).select("point_id", "dist"), 6, "dist")


@query
def ball_join_suppliers(spark, d):
    s = src.load(spark, d, "supplier")
    centers = src.points_from(s, "s_suppkey", [F.col("s_acctbal") / 1000, F.lit(0.4) * F.col("s_nationkey")], F.lit(0))
    return rounded(joins.ball_join(src.cust2d(spark, d), centers, 0.5, 2), 6, "dist")


@query
def nearest_two_centers(spark, d):
    pts = src.cust2d(spark, d)
    return rounded(joins.nearest_centers(pts, anchors(pts), 2), 6, "dist")


@query
def farthest_customers(spark, d):
    """A top-20 report of the worst served customers."""
    pts = src.cust2d(spark, d)
    return rounded(joins.farthest_points(pts, anchors(pts), 20), 6, "dist")


@query
def distance_profile(spark, d):
    pts = src.cust2d(spark, d)
    return rounded(measures.distance_profile(pts, anchors(pts)), 6, "p50", "p90", "p99", "cost")


@query
def partition_check(spark, d):
    pts = src.cust2d(spark, d)
    shards = distributed.shard_points(pts, 10)
    return pts.agg(F.count("*").alias("points"), F.count_distinct("point_id").alias("dealt")).crossJoin(joins.partition_check(pts, shards))


@query
def points_sent(spark, d):
    """Representatives that 10 workers send for a total budget of 240."""
    return measures.points_sent(distributed.worker_budget(src.cust2d(spark, d), 24, 10, how="modulo"))


@query
def distance_counters(spark, d):
    """Distance evaluations of greedy workers, plain and pruned."""
    return distance_evaluations(src.cust2d(spark, d), 24, 4, how="modulo")


@query
def cost_bound_check(spark, d):
    """The cost bound from the net alone holds: net cost plus twice the covering radius."""
    pts = staged(src.cust2d(spark, d), "points")
    net = staged(_net1(spark, d), "net")
    c = staged(nets.solve_on_net(net, FIVE_TWO), "centers")
    cover = nets.check_net(net, pts, 1.0, 1.0).first().covering
    real, core = measures.cost(pts, c).first().cost, measures.cost(net, c).first().cost
    bound = measures.cost_bound(net, c, cover)
    out = spark.createDataFrame([(pts.count(), real, core, cover, bound, real <= bound)], "points long, cost double, net_cost double, covering double, bound double, bound_holds boolean")
    return rounded(out, 6, "cost", "net_cost", "covering", "bound")


@query
def solver_plugged_in(spark, d):
    """The exact solver in place of the static one, on the labelled copies of the nations' net: their number and the optimum over them."""
    pts, caps = staged(src.nation_points(spark, d), "nations"), dict.fromkeys(range(5), 1)
    sent = staged(distributed.worker_net(pts, 5, 1 / 3, 3, how="modulo"), "worker-nets")
    net = staged(distributed.coordinator_net(sent, 1 / 3), "net")
    copies = nets.expand_labels(net).select(F.monotonically_increasing_id().alias("point_id"), "grp", "vec")
    copies = staged(copies, "copies")
    best = nets.solve_on_net(net, caps, "exact", keep_all=True, lift=False)
    return spark.createDataFrame([(copies.count(), measures.cost(copies, best).first().cost)], "copies long, net_optimum double").withColumn("net_optimum", F.round("net_optimum", 6))


@query
def uniform_scaling(spark, d):
    """Both distributed methods on the generated uniform set at growing sizes: seconds (mean of 3 runs), points sent and cost."""
    rows, caps = [], dict.fromkeys(range(4), 2)
    for n in (5_000, 20_000):
        pts = staged(src.uniform_points(spark, n, 50), "uniform")
        for name in ("distributed", "prior_distributed"):
            (c, held), s = measures.timed(lambda pts=pts, name=name: report.run_method(name, pts, caps, budget=800, shards=100))
            rows.append((name, n, s, held, float(measures.cost(pts, c).first().cost)))
    return spark.createDataFrame(rows, "method string, points long, seconds double, points_held long, cost double")


def _by_window(spark, d, width, slide):
    e = src.load(spark, d, "events")
    pts = src.evt4(spark, d).join(e.select(F.col("event_id").alias("point_id"), "ts"), "point_id")
    w = stream.window_summaries(pts, "ts", FIVE_TWO, width, slide)
    return w.select(src.day_number("start").alias("start_day"), "rank", "point_id", "grp")


@query
def window_summaries(spark, d):
    """Fair centers of every day of events."""
    return _by_window(spark, d, "1 day", None)


@query
def sliding_window_summaries(spark, d):
    """Fair centers of every two days of events, a window starting each day."""
    return _by_window(spark, d, "2 days", "1 day")


@query
def representation_greedy(spark, d):
    """How plain k-center represents the segments."""
    pts = src.cust2d(spark, d)
    pivots, _ = farthest_first_rounds(pts, 10)
    ids = [p for p, *_ in pivots]
    centers = pts.where(F.col("point_id").isin(ids))
    out = measures.representation(pts, centers, FIVE_TWO).select("grp", "points", "used", "point_share", "center_share")
    return rounded(out, 6, "point_share", "center_share")


def _net_state(spark, pts, net, r):
    """One row: size, points held, radius, packing, covering and the sum of representatives of a one-pass net."""
    c = nets.check_net(net, pts, 0.0, 1.0).first()
    reps = net.agg(F.sum(F.aggregate("reps.point_id", F.lit(0).cast("long"), lambda a, x: a + x)).alias("s")).first().s
    row = (pts.count(), c.net_points, measures.points_held(net).first()[0], float(r), c.least_gap, c.covering, reps)
    out = spark.createDataFrame([row], "points long, net_points long, points_held long, r double, least_gap double, covering double, id_sum long")
    return rounded(out, 6, "r", "least_gap", "covering")


@query
def budget_net_invariants(spark, d):
    """The budgeted one-pass net: at most 60 points, more than 4r apart, within 8r of all rows."""
    pts = src.cust2d(spark, d)
    return _net_state(spark, pts, staged(onepass.one_pass_budget_net(pts, 60), "net"), onepass.budget_trace(pts, 60, 1 << 40).first().r)


@query
def incremental_net_invariants(spark, d):
    """Packing eps r / 2 and covering eps r of the guaranteed one-pass net, r from the radius tracker over the same rows."""
    pts = src.cust2d(spark, d)
    return _net_state(spark, pts, staged(onepass.one_pass_net(pts, 10, 1 / 3), "net"), onepass.budget_trace(pts, 10, 1 << 40).first().r)


@query
def hierarchical_merge_check(spark, d):
    """The net of two merge levels with halving radii."""
    s = staged(distributed.worker_net(src.cust2d(spark, d), 10, 1 / 3, 16, how="modulo"), "worker-nets")
    return distributed.coordinator_net(s, 1 / 3, levels=2, fan_in=4).select("net_id", "groups")


@query
def budget_trace(spark, d):
    return rounded(onepass.budget_trace(src.cust2d(spark, d), 60, 100), 6, "r")


@query
def radius_doublings(spark, d):
    return stream.radius_growth(rounded(onepass.budget_trace(src.cust2d(spark, d), 24, 10), 6, "r")).withColumn("factor", F.round("factor", 6))


@query
def coreset_distortion_check(spark, d):
    pts = src.cust2d(spark, d)
    net = staged(_net1(spark, d), "net")
    c = centers_frame(spark, range(5), range(5), anchors(pts))
    r = nets.coreset_distortion(net, pts, c).select(F.lit(pts.count()).cast("long").alias("points"), F.lit(net.count()).cast("long").alias("net_points"), "core_cost", "full_cost", "distortion")
    return rounded(r, 6, "core_cost", "full_cost", "distortion")


@query
def feasibility_check(spark, d):
    c = distributed.distributed_fair_centers_budget(src.cust2d(spark, d), FIVE_TWO, 24, 4, how="modulo")
    return measures.feasibility(c, FIVE_TWO)


@query
def distributed_centers(spark, d):
    pts = staged(src.cust2d(spark, d), "points")
    return solved(pts, distributed.distributed_fair_centers(pts, FIVE_TWO, 1.0, 4, how="modulo"), 10)


@query
def distributed_budget_centers(spark, d):
    pts = staged(src.line6(spark, d), "points")
    return solved(pts, distributed.distributed_fair_centers_budget(pts, TWO_TEN, budget_total=240, shards=10, how="modulo"), 20)


@query
def distributed_budget_located_center(spark, d):
    pts = staged(src.line6(spark, d, 5), "points")
    return solved(pts, distributed.distributed_fair_centers_budget(pts, FIVE_TEN, 24, 10, how="modulo", located="center"), 50)


@query
def single_scan_workers(spark, d):
    """Workers that read what their task reads, in one pass: here four tasks, dealt by id."""
    pts = staged(src.cust2d(spark, d), "points")
    tasks = pts.repartitionById(4, (F.col("point_id") % 4).cast("int")).sortWithinPartitions("point_id")
    return solved(pts, distributed.distributed_fair_centers_budget(tasks, FIVE_TWO, 24, worker="single_scan"), 10)


@query
def one_pass_centers(spark, d):
    pts = staged(src.cust2d(spark, d), "points")
    return solved(pts, onepass.one_pass_fair_centers(pts, FIVE_TWO, 1.0), 10)


@query
def one_pass_budget_centers(spark, d):
    pts = staged(src.cust2d(spark, d), "points")
    return solved(pts, onepass.one_pass_fair_centers_budget(pts, FIVE_TWO, 60), 10)


@query
def sharded_one_pass_centers(spark, d):
    pts = staged(src.cust2d(spark, d), "points")
    return solved(pts, onepass.sharded_fair_centers(pts, FIVE_TWO, 1.0, 4, how="modulo"), 10)


@query
def static_centers(spark, d):
    pts = staged(src.line6(spark, d), "points")
    return solved(pts, static.static_fair_centers(pts, TWO_TEN, fill="greedy"), 20)


@query
def static_rounds_centers(spark, d):
    pts = staged(src.cust2d(spark, d), "points")
    return solved(pts, static.static_fair_centers(pts, FIVE_TWO, where="rounds"), 10)


@query
def static_filled_centers(spark, d):
    """Spare capacity spent on the farthest allowed points, where capacities bind."""
    pts = staged(src.corr4(spark, d), "points")
    return solved(pts, static.static_fair_centers(pts, SKEWED, fill="greedy"), 20)


@query
def two_pass_centers(spark, d):
    pts = staged(src.cust2d(spark, d), "points")
    return solved(pts, baselines.two_pass_fair_centers(pts, FIVE_TWO, 0.1), 10)


@query
def two_pass_correlated(spark, d):
    """The two-pass baseline where capacities bind."""
    pts = staged(src.corr4(spark, d), "points")
    return solved(pts, baselines.two_pass_fair_centers(pts, SKEWED, 0.1), 20)


@query
def prior_distributed_centers(spark, d):
    pts = staged(src.line6(spark, d), "points")
    return solved(pts, baselines.prior_distributed_fair_centers(pts, TWO_TEN, 0.1, 10, how="modulo"), 20)


@query
def random_centers(spark, d):
    pts = staged(src.line6(spark, d), "points")
    return solved(pts, baselines.random_fair_centers(pts, TWO_TEN), 20)


@query
def plain_k_center(spark, d):
    """One group: every path must handle plain k-center."""
    pts, caps = staged(src.cust2d(spark, d).withColumn("grp", F.lit(0)), "points"), {0: 10}
    runs = {
        "static": lambda: static.static_fair_centers(pts, caps),
        "two_pass": lambda: baselines.two_pass_fair_centers(pts, caps, 0.1),
        "prior_distributed": lambda: baselines.prior_distributed_fair_centers(pts, caps, 0.1, 4, how="modulo"),
        "distributed": lambda: distributed.distributed_fair_centers(pts, caps, 1.0, 4, how="modulo"),
        "distributed_budget": lambda: distributed.distributed_fair_centers_budget(pts, caps, 24, 4, how="modulo"),
        "one_pass": lambda: onepass.one_pass_fair_centers(pts, caps, 3.0),
        "one_pass_budget": lambda: onepass.one_pass_fair_centers_budget(pts, caps, 24),
        "sharded": lambda: onepass.sharded_fair_centers(pts, caps, 3.0, 4, how="modulo"),
    }
    out = [run().select(F.lit(name).alias("method"), "rank", "point_id") for name, run in runs.items()]
    return reduce(DataFrame.union, out)


@query
def binding_capacities(spark, d):
    """Groups that follow a feature, with skewed capacities: fairness has a price."""
    pts = staged(src.corr4(spark, d), "points")
    fair, plain = measures.cost(pts, static.static_fair_centers(pts, SKEWED)).first().cost, greedy_pivots(pts, 20)[1]
    out = spark.createDataFrame([(pts.count(), fair, plain, fair / plain)], "points long, fair_cost double, plain_cost double, price double")
    return rounded(out, 6, "fair_cost", "plain_cost", "price")


@query
def budget_sweep(spark, d):
    out = report.budget_sweep(src.cust2d(spark, d), FIVE_TWO, (5, 10, 20, 40, 80), 4, how="modulo")
    return rounded(out, 6, "coverage", "cost")


@query
def eps_sweep(spark, d):
    return rounded(report.eps_sweep(src.cust2d(spark, d), FIVE_TWO, how="modulo"), 6, "cost")


@query
def guaranteed_orders(spark, d):
    """Guaranteed distributed method on the larger two-dimensional set."""
    pts = staged(src.ord2d(spark, d), "points")
    return solved(pts, distributed.distributed_fair_centers(pts, dict.fromkeys(range(3), 10), 3.0, 8, how="modulo"), 30)


@query
def cost_ratio_customer(spark, d):
    pts = staged(src.cust2d(spark, d), "points")
    out = measures.cost_ratio(pts, distributed.distributed_fair_centers_budget(pts, FIVE_TWO, 24, 4, how="modulo"), 10)
    return rounded(out, 6, "cost", "greedy_radius", "ratio_greedy", "ratio_true")


@query
def doubling_dimension_customer(spark, d):
    return rounded(spark.createDataFrame([(measures.doubling_dimension(src.cust2d(spark, d), 1.0),)], "dimension double"), 6, "dimension")


@query
def smallest_sufficient_budget(spark, d):
    pts = staged(src.cust2d(spark, d), "points")
    b = distributed.smallest_budget(pts, [20, 40, 80, 160, 320], 3.0, 10, 4, how="modulo")
    return spark.createDataFrame([(b,)], "budget long")


@query
def checkpoint_report(spark, d):
    """A report every 2,500 of the first 32,500 rows: the one-pass method, its replay from scratch and the two-pass baseline on the prefix, seconds as means of 3 runs."""
    pts = staged(src.line6(spark, d), "points")
    return onepass.mean_checkpoints(pts, TWO_TEN, 3, every=2500, upto=32_500, budget=240, restart=True, two_pass=True)


def _report(name, groups=None):
    def run(spark, d):
        return report.workload_table(spark, d, only={name: groups or src.WORKLOAD_GROUPS[name]})

    QUERIES[f"report_{name}"] = run


for _name in src.WORKLOADS:
    _report(_name)


def _small_report(name):
    def run(spark, d):
        """The first 1,000 points of a set on 40 shards (the workload's own limit)."""
        return report.workload_table(spark, d, first=1000, shards=40, only={name: src.WORKLOAD_GROUPS[name]})

    QUERIES[f"report_small_{name}"] = run


for _name in ("rankings", "scores", "census", "documents"):
    _small_report(_name)


def _wide_report(dim, methods):
    def run(spark, d):
        """Labelled documents as points of very many dimensions."""
        return report.compare(src.dochash(spark, d, dim, packed=dim > 4096), TWO_TEN, methods, workload=f"documents_{dim}")

    QUERIES[f"report_documents_{dim}"] = run


_wide_report(1024, report.METHODS)
_wide_report(15_360, ("one_pass", "distributed"))


@query
def uniform_wide(spark, d):
    """The budgeted distributed method on 2,000 generated points of 1,000 dimensions: 800 points over 100 shards."""
    pts, caps = staged(src.uniform_points(spark, 2_000, 1000), "uniform"), dict.fromkeys(range(4), 2)
    (c, held), s = measures.timed(lambda: report.run_method("distributed", pts, caps, budget=800, shards=100), 1)
    return spark.createDataFrame([("distributed", s, held, float(measures.cost(pts, c).first().cost))], "method string, seconds double, points_held long, cost double")


@query
def uniform_generated(spark, d):
    """The generated uniform set through the budgeted distributed method: 8 centers per shard."""
    pts, caps = staged(src.uniform_points(spark, 20_000, 50), "uniform"), dict.fromkeys(range(4), 10)
    return measures.cost(pts, distributed.distributed_fair_centers_budget(pts, caps, budget_total=800, shards=100))


@query
def pages_by_host(spark, d):
    pts, caps = staged(src.page_points(spark, d, hash="md5"), "pages"), dict.fromkeys(range(6), 5)
    return solved(pts, distributed.distributed_fair_centers_budget(pts, caps, 24, 5, how="modulo"), 30)


@query
def conversations_by_role(spark, d):
    pts, caps = staged(src.conversation_points(spark, d, hash="md5"), "turns"), dict.fromkeys(range(3), 5)
    return solved(pts, distributed.distributed_fair_centers_budget(pts, caps, 24, 5, how="modulo"), 15)


@query
def benchmark_coverage(spark, d):
    """How far benchmark items are from fair centers of the documents."""
    docs = staged(src.doclang(spark, d, 64, hash="md5"), "docs")
    c = distributed.distributed_fair_centers_budget(docs, dict.fromkeys(range(4), 5), 24, 10, how="modulo")
    return rounded(measures.cost(src.benchmark_points(spark, d, 64, hash="md5"), c), 6, "cost")


@query
def user_ranking_centers(spark, d):
    pts = staged(src.user_rankings(spark, d), "users")
    return solved(pts, onepass.one_pass_fair_centers_budget(pts, FIVE_TWO, 30), 10)


@query
def text_hash_features(spark, d):
    """Sums over the signed token counts of every document."""
    docs = src.load(spark, d, "documents").select("doc_id", "text").withColumn("grp", F.lit(0))
    pts = src.hashed_points(docs, "doc_id", "grp", "text", 64, hash="md5")
    total = lambda f: F.aggregate(F.transform("vec", f), F.lit(0.0), lambda a, x: a + x).cast("long")
    return pts.select("point_id", total(F.abs).alias("norm"), total(lambda x, i: x * (i + 1)).alias("weighted"))


@query
def hourly_event_groups(spark, d):
    return rounded(stream.hourly_groups(src.load(spark, d, "events")), 4, "value")


@query
def session_events(spark, d):
    return stream.sessions(src.load(spark, d, "events"))


def _streamed(spark, d, mode):
    """Events as a stream of three files in order of arrival, through two shards."""
    pts = staged(src.evt4(spark, d), "event-points")
    base, n = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}", pts.agg(F.max("point_id")).first()[0]
    for i in range(3):
        pts.where((F.col("point_id") * 3 > i * n) & (F.col("point_id") * 3 <= (i + 1) * n) | (F.lit(i == 0) & (F.col("point_id") <= 0))).coalesce(1).write.mode("append").parquet(f"{base}/in")
    caps = dict.fromkeys(range(5), 4)
    run = stream.StreamingFairCenters(caps, mode, budget=60, eps=6.0, shards=2, how="modulo")
    run.start(stream.stream_points(spark, f"{base}/in", src.POINT), f"{base}/out", f"{base}/checkpoint").awaitTermination()
    return solved(pts, run.centers(spark, f"{base}/out"), 20)


@query
def streaming_sharded_centers(spark, d):
    return _streamed(spark, d, "budget")


@query
def streaming_guaranteed_centers(spark, d):
    return _streamed(spark, d, "guaranteed")


@query
def streaming_versioned_nets(spark, d):
    """Every version of one merged net over events in three files: what it has seen, the groups in it, and whether it packs and covers what it saw."""
    pts = staged(src.evt4(spark, d), "event-points")
    base, n = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}", pts.agg(F.max("point_id")).first()[0]
    third = lambda i: F.ceil(F.col("point_id") * 3 / F.lit(n)) <= i
    job, rows = stream.VersionedFairCenters(dict.fromkeys(range(5), 4), eps=3.0, shards=2, how="modulo"), []
    for i in (1, 2, 3):
        pts.where(third(i) & ~third(i - 1) if i > 1 else third(1)).coalesce(1).write.mode("append").parquet(f"{base}/in")
        job.start(stream.stream_points(spark, f"{base}/in", src.POINT), f"{base}/out", f"{base}/checkpoint").awaitTermination()
        net = staged(job.newest(spark, f"{base}/out"), "version")
        of = net.agg(F.max("radius").alias("radius"), F.max("seen").alias("seen"), F.bit_or("groups").alias("groups")).first()
        sound = nets.check_net(net, pts.where(third(i)), job.eps_bar * of.radius, 2.0).first()
        rows.append((i, of.seen, of.groups, sound.packed, sound.covered))
    return spark.createDataFrame(rows, "version int, seen long, groups long, packed boolean, covered boolean")


@query
def net_aggregate_customer(spark, d):
    """Nets of four shards of the customers by the aggregate function: net points and the representatives they hold."""
    register_sql(spark)
    shard = F.pmod("point_id", F.lit(4)).alias("shard")
    nested = src.cust2d(spark, d).groupBy(shard).agg(net_agg(1.0)("point_id", "grp", "vec").alias("net"))
    n = nested.select("shard", F.explode("net").alias("n"))
    return n.select("shard", "n.net_id", "n.grp", F.col("n.point_id").alias("rep_id"), F.round("n.dist", 6).alias("dist"))


@query
def sql_distances(spark, d):
    """Distances to the origin's neighbour (1, 1) by the registered SQL functions."""
    register_sql(spark)
    to_one = lambda m: F.expr(f"round({m}_distance(vec, array(1D, 1D)), 6)").alias(m)
    return src.cust2d(spark, d).select("point_id", *(to_one(m) for m in ("l1", "l2", "linf", "hamming")))


@query
def sql_surface(spark, d):
    register_sql(spark)
    pts = staged(src.cust2d(spark, d).withColumn("shard", F.col("point_id") % 4), "points")
    name = f"points_{uuid.uuid4().hex}"
    pts.createOrReplaceTempView(name)
    spark.sql(f"SELECT * FROM net_summary(TABLE({name}) PARTITION BY (shard) ORDER BY (point_id), 24)").createOrReplaceTempView(f"{name}_net")
    caps = '{"0": 2, "1": 2, "2": 2, "3": 2, "4": 2}'
    centers = spark.sql(f"SELECT * FROM fair_centers(TABLE(SELECT member_id, member_grp, member FROM {name}_net) WITH SINGLE PARTITION, '{caps}')")
    out = solved(pts, centers, 10)
    spark.catalog.dropTempView(name), spark.catalog.dropTempView(f"{name}_net")
    return out


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Budgeted distributed centers of the customers, two per market segment, with each center's distance profile."""
    pts = src.cust2d(spark, d)
    centers = staged(distributed.distributed_fair_centers_budget(pts, FIVE_TWO, 24, 4), "centers")
    a = with_distance(pts, measures.center_vectors(centers), "l1", "dist", "rank")
    return centers.join(a.groupBy("rank").agg(F.count("*").alias("points"), F.max("dist").alias("farthest")), "rank", "left").select("rank", "point_id", "grp", "points", "farthest")
