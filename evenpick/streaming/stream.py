"""Streaming fair centers.

Each shard keeps a net in keyed state; every micro-batch updates it with the batch's rows (sorted by id inside the batch) and writes
the shard's new summary. A query merges the newest summary of each shard and solves, without reading the stream again.
Insertions only: there is no way to take a row back.
"""

from __future__ import annotations

import pickle
from collections.abc import Mapping
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from evenpick.functions.kernels import BudgetNet, IncrementalNet, Net, farthest_first, merge_nets
from evenpick.functions.metrics import metric
from evenpick.functions.solver import check_caps
from evenpick.operators.distributed import coordinator_net, worker_net
from evenpick.operators.frames import NET, SUMMARY, arrays, net_of, net_rows, shard_points, shards_for
from evenpick.operators.nets import solve_on_net
from evenpick.plans.durable import ship_package, staged
from evenpick.sources.points import uniform_columns

VERSIONED = f"{SUMMARY}, version long"
VERSION = f"radius double, seen long, {NET}"


def stream_points(spark: SparkSession, folder: str, schema: str, files_per_trigger: int = 1) -> DataFrame:
    """Parquet files of a folder as a stream."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)


def rate_points(spark: SparkSession, rows_per_second: int = 1000, dim: int = 10, groups: int = 4, scale: float = 1e5, seed: int = 7) -> DataFrame:
    """Endless uniform points for soak tests: the rate source's counter is the id, coordinates are hashes of (id, dimension)."""
    rows = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    return uniform_columns(rows.withColumnRenamed("value", "id"), dim, groups, scale, seed)


def insert_only(points: DataFrame, op: str, inserts: tuple[str, ...] = ("insert", "i", "c")) -> DataFrame:
    """Points of a change feed whose column ``op`` names the change; a change other than an insert stops the job, as nets take nothing back.

    A null change counts as no insert.
    """
    taken = F.coalesce(F.lower(op).isin(*inserts), F.lit(False))
    refused = F.raise_error(F.concat(F.lit("insert-only stream, got: "), F.coalesce(F.col(op), F.lit("null"))))
    return points.where(F.when(taken, F.lit(True)).otherwise(refused.cast("boolean"))).drop(op)


def deduplicated(stream: DataFrame, ts: str, delay: str = "1 hour") -> DataFrame:
    """Replayed ids dropped within a watermark (late rows themselves are welcome: the nets are insert-only)."""
    return stream.withColumn("event_time", F.col(ts).cast("timestamp")).withWatermark("event_time", delay).dropDuplicatesWithinWatermark(["point_id"])


@dataclass(frozen=True)
class StreamingFairCenters:
    """``mode``: 'budget' (memory bound) or 'guaranteed' (factor 3(1 + eps))."""

    caps: Mapping[int, int]
    mode: str = "budget"
    budget: int = 240
    eps: float = 1.0
    shards: int = 4
    metric: str = "l1"
    how: str = "hash"

    def _fresh(self):
        k = sum(check_caps(self.caps).values())
        return BudgetNet(self.budget, self.metric) if self.mode == "budget" else IncrementalNet(k, self.eps / 6, self.metric)

    def summaries(self, points: DataFrame) -> DataFrame:
        """Streaming summaries: after a micro-batch, all net rows of the shards it touched, under a new version."""
        ship_package(points.sparkSession)

        def update(key, batches, state: GroupState):
            net, version = pickle.loads(state.get[0]) if state.exists else (self._fresh(), 0)
            rows = [b for b in batches if len(b)]
            if rows:
                net.insert_block(*arrays(rows[0] if len(rows) == 1 else pd.concat(rows)))
                version += 1
            state.update((pickle.dumps((net, version)),))
            yield net_rows(net.net, shard=int(key[0]), r_t=float(net.r), n_t=int(net.seen)).assign(version=version)

        keyed = shard_points(points, self.shards, self.how).select("shard", "point_id", "grp", "vec")
        return keyed.groupBy("shard").applyInPandasWithState(update, VERSIONED, "net binary", "append", GroupStateTimeout.NoTimeout)

    def start(self, points: DataFrame, out: str, checkpoint: str, once: bool = True):
        """Write versions of the shard summaries as Parquet under ``out`` (one folder per micro-batch, so a replayed batch overwrites itself)."""

        def save(batch: DataFrame, number: int) -> None:
            batch.write.mode("overwrite").parquet(f"{out}/batch={number}")

        writer = self.summaries(points).writeStream.outputMode("append").option("checkpointLocation", checkpoint).foreachBatch(save)
        return (writer.trigger(availableNow=True) if once else writer).start()

    def newest(self, spark: SparkSession, out: str) -> DataFrame:
        """SUMMARY: the newest version of every shard."""
        rows = spark.read.schema(VERSIONED + ", batch long").parquet(out)
        last = rows.groupBy("shard").agg(F.max("version").alias("version"))
        return rows.join(F.broadcast(last), ["shard", "version"]).drop("version", "batch")

    def centers(self, spark: SparkSession, out: str) -> DataFrame:
        """CENTER for everything seen so far."""
        return self.solve(self.newest(spark, out))

    def solve(self, summaries: DataFrame) -> DataFrame:
        if self.mode == "budget":
            return solve_on_net(summaries.select("net_id", "vec", "grp", "groups", "reps"), self.caps, "static", self.metric, located="rep")
        return solve_on_net(coordinator_net(summaries, self.eps / 12, self.metric), self.caps, "static", self.metric)


@dataclass(frozen=True)
class VersionedFairCenters:
    """One net for the whole stream, a version per micro-batch, in place of keyed state; factor 3(1 + eps).

    Tasks reduce a batch to nets of its shards, which are folded into the newest version with the radius that version was built for. Once
    the batch, or the net itself, shows a scale above that radius, the radius at least doubles and the old net is thinned first; so
    what a version is off by stays below twice its own absorbing distance, however many batches there were. A batch that runs again after
    a failure folds into the version before it and overwrites its own, and a query reads the newest complete version alone.
    """

    caps: Mapping[int, int]
    eps: float = 1.0
    shards: int | None = None
    metric: str = "l1"
    how: str = "hash"

    @property
    def eps_bar(self) -> float:
        return self.eps / 6

    def folded(self, old: DataFrame | None, batch: DataFrame) -> DataFrame:
        """VERSION of everything in ``old`` (None: nothing yet) and the batch."""
        k, eps_bar, name = sum(check_caps(self.caps).values()), self.eps_bar, metric(self.metric).name
        batch = staged(batch.select("point_id", "grp", "vec"), "micro-batch")
        fresh = worker_net(batch, k, eps_bar, shards_for(batch, self.shards), name, self.how)
        if old is not None:
            fresh = fresh.unionByName(old.select(F.lit(-1).cast("long").alias("shard"), F.col("radius").alias("r_t"), F.col("seen").alias("n_t"), "net_id", "vec", "grp", "groups", "reps"))
        ship_package(batch.sparkSession)

        def run(pdf: pd.DataFrame) -> pd.DataFrame:
            held = pdf.shard < 0
            radius = float(pdf.r_t[held].max()) if held.any() else 0.0
            net = net_of(pdf[held].sort_values("net_id", kind="stable"))

            def grown(net: Net, scale: float) -> tuple[Net, float]:
                wide = radius if 2 * scale <= radius else max(2 * radius, 2 * scale)
                return (merge_nets(net, Net(), eps_bar * wide, name) if wide > radius and len(net) else net), wide

            net, radius = grown(net, float(pdf.r_t[~held].max()) if (~held).any() else 0.0)
            for _, part in sorted(pdf[~held].groupby("shard")):
                net = merge_nets(net_of(part.sort_values("net_id", kind="stable")), net, eps_bar * radius, name)
            net, radius = grown(net, farthest_first(net.matrix(), k, name)[2] / 8)
            return net_rows(net, radius=radius, seen=int(pdf.drop_duplicates("shard").n_t.sum()))

        return fresh.withColumn("bucket", F.lit(0)).groupBy("bucket").applyInPandas(run, VERSION)

    def start(self, points: DataFrame, out: str, checkpoint: str, once: bool = True):
        """Write the versions under ``out``, one folder each."""

        def save(batch: DataFrame, number: int) -> None:
            spark = batch.sparkSession
            before = [v for v in self.versions(spark, out) if v < number]
            old = self.version(spark, out, before[-1]) if before else None
            self.folded(old, batch).write.mode("overwrite").parquet(f"{out}/version={number}")

        writer = points.writeStream.outputMode("append").option("checkpointLocation", checkpoint).foreachBatch(save)
        return (writer.trigger(availableNow=True) if once else writer).start()

    def versions(self, spark: SparkSession, out: str) -> list[int]:
        """Numbers of the complete versions, ascending, from the folder listing alone."""
        done = spark._jvm.org.apache.hadoop.fs.Path(f"{out}/version=*/_SUCCESS")
        found = done.getFileSystem(spark._jsc.hadoopConfiguration()).globStatus(done)
        return sorted(int(f.getPath().getParent().getName().split("=")[1]) for f in found or [])

    def version(self, spark: SparkSession, out: str, number: int) -> DataFrame:
        return spark.read.schema(VERSION).parquet(f"{out}/version={number}")

    def newest(self, spark: SparkSession, out: str) -> DataFrame:
        """VERSION of everything seen so far (empty before the first batch)."""
        found = self.versions(spark, out)
        return self.version(spark, out, found[-1]) if found else spark.createDataFrame([], VERSION)

    def centers(self, spark: SparkSession, out: str) -> DataFrame:
        """CENTER for everything seen so far."""
        return solve_on_net(self.newest(spark, out).drop("radius", "seen"), self.caps, "static", self.metric)


def window_summaries(points: DataFrame, ts: str, caps: Mapping[int, int], width: str = "1 day", slide: str | None = None, budget: int = 60, m: str = "l1") -> DataFrame:
    """(start, stop, rank, point_id, grp, vec): fair centers of every tumbling or sliding window. Batch or stream.

    A window is reduced to a budget net inside its group, so what the solver sees is bounded.
    """
    from evenpick.functions.solver import solve_static
    from evenpick.operators.frames import matrix

    caps = check_caps(caps)
    ship_package(points.sparkSession)

    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        net = BudgetNet(budget, m)
        net.insert_block(*arrays(pdf))
        held = {p: (v, g) for r in net.net.reps for g, (p, v, _) in r.items()}
        ids = sorted(i for i in held if caps.get(held[i][1], 0) > 0)
        if not ids:
            return pd.DataFrame({"start": [], "stop": [], "rank": [], "point_id": [], "grp": [], "vec": []})
        x, grp = matrix([held[i][0] for i in ids]), [held[i][1] for i in ids]
        rows = solve_static(x, pd.Series(grp).to_numpy(), caps, m).rows
        return pd.DataFrame({"start": key[0]["start"], "stop": key[0]["end"], "rank": range(len(rows)), "point_id": [ids[i] for i in rows], "grp": [grp[i] for i in rows], "vec": [x[i].tolist() for i in rows]})

    w = F.window(F.col(ts).cast("timestamp"), width, slide or width)
    return points.withColumn("w", w).select("w", "point_id", "grp", "vec").groupBy("w").applyInPandas(run, "start timestamp, stop timestamp, rank int, point_id long, grp int, vec array<double>")


def hourly_groups(events: DataFrame) -> DataFrame:
    """Events per hour and type (batch twin of a tumbling-window count)."""
    w = F.window(F.col("ts").cast("timestamp"), "1 hour")
    return events.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("events"), F.sum("value").alias("value")).select(F.col("w.start").cast("timestamp_ntz").alias("hour"), "event_type", "events", "value")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """Sessions per user: (user_id, start, events)."""
    s = F.session_window(F.col("ts").cast("timestamp"), gap)
    return events.groupBy("user_id", s.alias("s")).agg(F.count("*").alias("events")).select("user_id", F.col("s.start").cast("timestamp_ntz").alias("start"), "events")


def radius_growth(trace: DataFrame) -> DataFrame:
    """Rows of a trace at which r grew, with the factor."""
    w = W.orderBy("n_seen")
    return trace.withColumn("before", F.lag("r").over(w)).where("r > before").withColumn("factor", F.col("r") / F.nullif("before", F.lit(0.0)))
