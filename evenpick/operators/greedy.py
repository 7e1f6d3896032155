"""Farthest-first greedy k-center: as DataFrame rounds over any amount of data, and inside one task per shard."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evenpick.functions.kernels import farthest_first, farthest_first_pruned, min_dist_block
from evenpick.functions.metrics import UNROLL_TERMS, Metric, metric
from evenpick.operators.frames import BLOCK_VALUES, blocks, for_driver, per_shard, point_arrays, rows_of, shard_points, unpack, vector_blocks, whole_numbers
from evenpick.plans.durable import checkpointed, ship_package

#: Vector components that the tasks of one greedy scan send to the driver together (32 MB of doubles).
SENT_VALUES = 4_000_000
PIVOT = "shard long, rank int, point_id long, delta double, radius double"


def _lower(points: DataFrame, vec: list[float], m: Metric) -> DataFrame:
    """``md``: the distance to the nearest pivot so far, after one more pivot."""
    return points.withColumn("md", F.least("md", m.to_point(F.col("vec"), vec)))


def farthest_first_rounds(points: DataFrame, k: int, m: Metric | str = "l1", every: int = 12) -> tuple[list[tuple[int, list[float], float]], float]:
    """([(point_id, vec, delta)], radius) by at most k scans; the driver holds pivots only. Lineage is cut every ``every`` rounds.

    With constants unrolled into one expression each round is one compiled pass; wide vectors take several pivots a scan.
    """
    m = metric(m)
    first = points.orderBy("point_id").select("point_id", "vec").first()
    if first is None:
        raise ValueError("no points")
    plain = lambda v: unpack(bytes(v)).tolist() if isinstance(v, (bytes, bytearray)) else list(v)
    held = [(first.point_id, plain(first.vec), float("inf"))]
    dim = len(held[0][1])
    if dim > UNROLL_TERMS // every:
        return _rounds_of_many(points.select("point_id", "vec"), held, k, m)
    df, done = points.select("point_id", "vec").withColumn("md", F.lit(float("inf"))), 0
    while True:
        for _, v, _ in held[done:]:
            df = _lower(df, v, m)
        if len(held) - done and len(held) % every == 0:
            df = checkpointed(df)
        done = len(held)
        far = df.agg(F.max_by(F.struct("point_id", "vec", "md"), F.struct(F.col("md"), -F.col("point_id"))).alias("p")).first().p
        if len(held) == k or far.md <= 0:
            return held, float(far.md)
        held.append((far.point_id, plain(far.vec), float(far.md)))


def _rounds_of_many(points: DataFrame, held: list, k: int, m: Metric) -> tuple[list[tuple[int, list[float], float]], float]:
    """The same pivots with several to a scan: tasks send their farthest rows and the next one as a bound.

    Distances only fall, so the farthest row sent is the farthest of all while it comes before every bound; then the next scan is due.
    """
    tasks = points.select(F.spark_partition_id().alias("task")).distinct().count()
    rows = max(1, SENT_VALUES // max(1, len(held[0][1])) // tasks)
    while True:
        sent = _farthest_rows(points, [v for _, v, _ in held], rows, m).toArrow()
        kept = sent.filter(sent["kept"])
        bound = max(((r["md"], -r["point_id"]) for r in sent.filter(pc.invert(sent["kept"])).select(["md", "point_id"]).to_pylist()), default=(-1.0, 0))
        ids, md, x = whole_numbers(kept["point_id"]), kept["md"].to_numpy().copy(), rows_of(kept["vec"])
        order = np.argsort(ids, kind="stable")  # argmax takes the first: the smaller id
        ids, md, x = ids[order], md[order], x[order]
        while (md[i := int(md.argmax())], -ids[i]) >= bound:
            if len(held) == k or md[i] <= 0:
                return held, float(md[i])
            held.append((int(ids[i]), x[i].tolist(), float(md[i])))
            md = np.minimum(md, m.one_to_many(x[i], x))


def _farthest_rows(points: DataFrame, centers: list[list[float]], rows: int, m: Metric) -> DataFrame:
    """(point_id, vec, md, kept): of every task the ``rows`` rows farthest from ``centers``, ties to the smaller id, and the next one, not kept."""
    ship_package(points.sparkSession)
    c, name = np.array(centers, float), m.name
    step = 8192 if points.schema["vec"].dataType.typeName() == "binary" else min(8192, max(1, BLOCK_VALUES // max(1, len(centers[0]))))

    def first(t: pa.Table) -> pa.Table:
        return t.take(pa.array(np.lexsort((whole_numbers(t["point_id"]), -t["md"].to_numpy()))[: rows + 1]))

    def run(batches):
        held, least = None, -np.inf
        for b in batches:
            if not b.num_rows:
                continue
            d = np.concatenate([min_dist_block(x, c, name, step)[0] for _, x in vector_blocks(b.column(1))])
            at = pa.array(np.flatnonzero(d >= least))
            part = pa.Table.from_batches([b]).append_column("md", pa.array(d)).take(at)
            held = part if held is None else pa.concat_tables([held, part])
            if held.num_rows > 2 * rows + 2:
                held = first(held)
                least = held["md"][-1].as_py()
        if held is not None:
            held = first(held)
            yield from held.append_column("kept", pa.array(np.arange(held.num_rows) < rows)).combine_chunks().to_batches()

    vec = points.schema["vec"].dataType.simpleString()
    return points.mapInArrow(run, f"point_id long, vec {vec}, md double, kept boolean")


def greedy_pivots(points: DataFrame, k: int, m: Metric | str = "l1", fits: bool | None = None) -> tuple[list[tuple[int, list[float], float]], float]:
    """As ``farthest_first_rounds``, in one driver run where the measured size allows it; both give the same pivots.

    Beyond that size copies are dropped first: a copy of a pivot is never a pivot, and of equal rows the least id is taken.
    ``fits``: where ``for_driver`` has been asked before, its answer.
    """
    points = points.withColumn("grp", F.lit(0))
    points, fits = for_driver(points) if fits is None else (points, fits)
    if not fits:
        return farthest_first_rounds(points, k, m)
    x, ids, _ = point_arrays(points)
    p, delta, radius, _, _ = farthest_first(x, k, m)
    return [(int(ids[i]), x[i].tolist(), float(e)) for i, e in zip(p, delta)], radius


def with_distance(points: DataFrame, centers: list[list[float]], m: Metric | str = "l1", into: str = "dist", index: str | None = None) -> DataFrame:
    """``points`` with the distance to the nearest of constant ``centers`` (and its index, first on ties).

    Few terms stay inside generated code; many go through the block kernel.
    """
    m = metric(m)
    terms = sum(len(c) for c in centers)
    if terms <= UNROLL_TERMS:
        dists = [m.to_point(F.col("vec"), c) for c in centers]
        best = F.least(*dists) if len(dists) > 1 else dists[0]
        out = points.withColumn(into, best)
        if index:
            at = F.lit(len(dists) - 1)
            for i in reversed(range(len(dists) - 1)):
                at = F.when(dists[i] <= F.col(into), i).otherwise(at)
            out = out.withColumn(index, at.cast("int"))
        return out
    ship_package(points.sparkSession)
    from evenpick.functions.kernels import min_dist_block

    c, name = np.array(centers, float), m.name

    def run(batches):
        for pdf in batches:
            if len(pdf):
                parts = [min_dist_block(x, c, name, min(8192, max(1, BLOCK_VALUES // max(1, c.shape[1])))) for _, x in blocks(pdf.vec.to_numpy())]
                d, i = (np.concatenate(p) for p in zip(*parts))
                pdf[into] = d
                if index:
                    pdf[index] = i.astype(np.int32)
                yield pdf

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in points.schema.fields) + f", `{into}` double" + (f", `{index}` int" if index else "")
    return points.mapInPandas(run, fields)


def farthest_first_per_shard(points: DataFrame, k: int, shards: int, m: Metric | str = "l1", how: str = "hash") -> DataFrame:
    """(shard, rank, point_id, delta, radius): every shard's greedy pivots and the radius they leave."""
    name = metric(m).name

    def run(shard, x, ids, grp):
        p, delta, radius, _, _ = farthest_first(x, k, name)
        return pd.DataFrame({"shard": shard, "rank": np.arange(len(p), dtype=np.int32), "point_id": ids[p], "delta": delta, "radius": radius})

    return per_shard(shard_points(points, shards, how), run, PIVOT)


def distance_evaluations(points: DataFrame, k: int, shards: int, m: Metric | str = "l1", how: str = "hash") -> DataFrame:
    """(shard, plain, pruned): distance evaluations of the greedy worker, and with pivots skipped by the triangle inequality."""
    name = metric(m).name

    def run(shard, x, ids, grp):
        p, *_, pruned = farthest_first_pruned(x, k, name)
        return pd.DataFrame({"shard": [shard], "plain": [len(x) * len(p)], "pruned": [pruned]})

    return per_shard(shard_points(points, shards, how), run, "shard long, plain long, pruned long")
