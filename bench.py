"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; one JSON line."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession

from evenpick.operators import baselines, distributed, measures, onepass, static
from evenpick.operators.greedy import greedy_pivots
from evenpick.plans.durable import staged
from evenpick.queries import QUERIES
from evenpick.sources import points as src

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
CAPS = dict.fromkeys(range(2), 10)


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    seconds: dict[str, float] = {}

    def timed(name, run):
        began = time.perf_counter()
        out = run()
        seconds[name] = round(time.perf_counter() - began, 3)
        return out

    census = timed("census_points", lambda: staged(src.line6(spark, SF_DIR), "census"))
    _, radius = timed("census_greedy_normaliser", lambda: greedy_pivots(census, 20))
    cost = {}
    runs = {
        "static": lambda: static.static_fair_centers(census, CAPS),
        "two_pass": lambda: baselines.two_pass_fair_centers(census, CAPS),
        "one_pass": lambda: onepass.one_pass_fair_centers_budget(census, CAPS, 240),
        "prior_distributed": lambda: baselines.prior_distributed_fair_centers(census, CAPS, shards=10),
        "distributed": lambda: distributed.distributed_fair_centers_budget(census, CAPS, budget_total=240, shards=10),
        "distributed_single_scan": lambda: distributed.distributed_fair_centers_budget(census, CAPS, 24, worker="single_scan"),
    }
    for name, run in runs.items():
        centers = timed(f"census_{name}", lambda run=run: measures.center_vectors(run()))
        cost[name] = round(timed(f"census_cost_{name}", lambda: measures.cost(census, centers).first().cost) / radius, 4)
    two = staged(src.cust2d(spark, SF_DIR), "customers")
    five = dict.fromkeys(range(5), 2)
    timed("customers_distributed_guaranteed", lambda: distributed.distributed_fair_centers(two, five, 3.0, 8).collect())
    timed("customers_one_pass_guaranteed", lambda: onepass.one_pass_fair_centers(two, five, 3.0).collect())
    for name in ("points_w1_rankings", "points_w2_scores", "aspect_ratio_embeddings", "streaming_sharded_centers", "ball_join_suppliers"):
        timed(name, lambda name=name: QUERIES[name](spark, SF_DIR).write.format("noop").mode("overwrite").save())
    try:
        from evenpick.llm.queries import QUERIES as llm
    except ImportError:
        llm = {}
    for name, run in llm.items():
        timed(name, lambda run=run: run(spark, SF_DIR).write.format("noop").mode("overwrite").save())
    print(json.dumps({"metric": "total_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "census_cost_ratios": cost, "sf": SF_DIR.rsplit("sf", 1)[-1], "census_points": census.count()}))
    spark.stop()


if __name__ == "__main__":
    main()
