import pytest
from pyspark.sql import functions as F

from evenpick.operators import measures, onepass
from evenpick.sources import points as src
from evenpick.streaming.stream import StreamingFairCenters, VersionedFairCenters, deduplicated, insert_only, rate_points, stream_points

CAPS = dict.fromkeys(range(5), 2)


@pytest.fixture(scope="module")
def points(spark, sf):
    return src.cust2d(spark, sf).cache()


def put(points, folder, lo, hi):
    points.where((F.col("point_id") >= lo) & (F.col("point_id") < hi)).coalesce(1).write.mode("append").parquet(folder)


def run(spark, job, base):
    job.start(stream_points(spark, f"{base}/in", src.POINT), f"{base}/out", f"{base}/checkpoint").awaitTermination()


@pytest.mark.parametrize("mode", ["budget", "guaranteed"])
def test_stream_equals_replay_across_a_restart(spark, points, tmp_path, mode):
    job = StreamingFairCenters(CAPS, mode, budget=30, eps=3.0, shards=1)
    put(points, f"{tmp_path}/in", 0, 60)
    run(spark, job, tmp_path)
    put(points, f"{tmp_path}/in", 60, 1000)
    run(spark, job, tmp_path)
    got = {(r.net_id, r.groups) for r in job.newest(spark, f"{tmp_path}/out").collect()}
    replay = onepass.one_pass_budget_net(points, 30) if mode == "budget" else onepass.one_pass_net(points, 10, 0.5)
    assert got == {(r.net_id, r.groups) for r in replay.collect()}
    centers = job.centers(spark, f"{tmp_path}/out")
    assert all(r.fits for r in measures.feasibility(centers, CAPS).collect())


def test_late_rows_are_taken_and_replayed_ids_dropped(spark, points, tmp_path):
    put(points, f"{tmp_path}/in", 50, 1000)
    put(points, f"{tmp_path}/in", 0, 50)
    job = StreamingFairCenters(CAPS, "budget", budget=30, shards=3)
    run(spark, job, tmp_path)
    assert job.newest(spark, f"{tmp_path}/out").groupBy("shard").agg(F.max("n_t").alias("n")).agg(F.sum("n")).first()[0] == points.count()
    timed = points.withColumn("ts", F.lit("2024-01-01 00:00:00").cast("timestamp_ntz"))
    timed.union(timed.limit(20)).coalesce(1).write.parquet(f"{tmp_path}/twice")
    s = deduplicated(spark.readStream.schema(timed.schema).parquet(f"{tmp_path}/twice"), "ts")
    q = s.writeStream.format("memory").queryName("once").option("checkpointLocation", f"{tmp_path}/c2").trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.table("once").count() == points.count()


def test_versions_fold_batches_and_survive_a_replayed_one(spark, points, tmp_path):
    from evenpick.operators import nets, static

    job, out = VersionedFairCenters(CAPS, eps=3.0, shards=2), f"{tmp_path}/out"
    assert job.newest(spark, out).count() == 0
    # three points show no scale for ten centers: kept as they are
    for lo, hi in ((0, 4), (4, 60), (60, 1000)):
        put(points, f"{tmp_path}/in", lo, hi)
        run(spark, job, tmp_path)
    assert job.versions(spark, out) == [0, 1, 2]
    first, last = (job.version(spark, out, v) for v in (0, 2))
    assert first.count() == points.where("point_id < 4").count() and first.first().radius == 0
    assert last.first().seen == points.count()
    radii = [job.version(spark, out, v).first().radius for v in range(3)]
    assert radii == sorted(radii) and radii[2] > 0
    sound = nets.check_net(last, points, job.eps_bar * radii[2], 2.0).first()
    assert sound.packed and sound.covered
    fair = measures.cost(points, static.static_fair_centers(points, CAPS)).first().cost
    # static lies within 3 of the optimum and no better than it; the radius never exceeds the optimum
    assert radii[2] <= fair
    centers = job.centers(spark, out)
    assert measures.cost(points, centers).first().cost <= 3 * (1 + 3.0) * fair and all(r.fits for r in measures.feasibility(centers, CAPS).collect())
    # a version left half-written does not count, and folding the last batch again gives the same version
    again = job.folded(job.version(spark, out, 1), points.where("point_id >= 60"))
    assert sorted(r.net_id for r in again.collect()) == sorted(r.net_id for r in last.collect())
    (tmp_path / "out" / "version=7").mkdir()
    assert job.versions(spark, out) == [0, 1, 2]


def test_many_small_batches_do_not_grow_the_net(spark):
    """Batches of one point each show no radius of their own; the net's own scale thins it."""
    job, net = VersionedFairCenters({0: 1, 1: 1}, eps=6.0, shards=1), None
    for i in range(12):
        row = spark.createDataFrame([(i, i % 2, [float(i % 6) * 0.01 + 10.0 * (i % 3)])], "point_id long, grp int, vec array<double>")
        net = spark.createDataFrame(job.folded(net, row).collect(), job.newest(spark, "/nowhere").schema)
    assert net.first().seen == 12 and net.first().radius > 0 and net.count() <= 6


def test_deletes_are_refused(spark):
    from pyspark.errors import PySparkException

    feed = spark.createDataFrame([(1, 0, [1.0], "insert"), (2, 0, [2.0], "I")], "point_id long, grp int, vec array<double>, op string")
    assert insert_only(feed, "op").columns == ["point_id", "grp", "vec"] and insert_only(feed, "op").count() == 2
    for op in ("delete", None):
        bad = feed.union(spark.createDataFrame([(1, 0, [1.0], op)], feed.schema))
        with pytest.raises(PySparkException, match="insert-only"):
            insert_only(bad, "op").collect()


def test_rate_source_gives_points(spark, tmp_path):
    from pyspark.sql.functions import size

    s = rate_points(spark, 200, dim=3, groups=2)
    q = s.writeStream.format("memory").queryName("rates").option("checkpointLocation", f"{tmp_path}/c").start()
    try:
        q.processAllAvailable()
        import time

        for _ in range(40):
            if spark.table("rates").count():
                break
            time.sleep(0.5)
    finally:
        q.stop()
    got = spark.table("rates").select("point_id", "grp", size("vec").alias("d")).collect()
    assert got and {r.d for r in got} == {3} and {r.grp for r in got} <= {0, 1}
    same = {r.point_id: r.grp for r in src.uniform_points(spark, max(r.point_id for r in got) + 1, 3, 2).collect()}
    assert all(same[r.point_id] == r.grp for r in got)
