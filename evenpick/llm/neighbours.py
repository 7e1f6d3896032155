"""Approximate nearest neighbours by multiprobe p-stable hashing.

Vectors are scaled to unit length, where Euclidean nearness and cosine order candidates alike. Each of several tables cuts a few
Gaussian projections into cells of one width; a query visits the cells around its own in the order of their estimated
success, and all candidates that its tables give are ranked by their exact cosine in double precision.

Index rows are dealt by (table, cell) and, where a cell is crowded, by a salt, so no task holds a hot cell whole; each query keeps only
its best few of each dealt block before the blocks are merged.

A query whose cells give fewer than asked is compared with all candidates of its length, block by block, so only queries with fewer
candidates get fewer rows.

Defined results: vectors that are null, zero or hold null or non-finite components take no part; a query with fewer candidates than
asked gets all of them, each vector length being a space of its own; equal scores go to the smaller id; rows that share an id are one candidate (the best of them);
an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass
from itertools import combinations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from evenpick.plans.durable import ship_package, staged

#: Rows of one cell that go to one task.
CELL_ROWS = 8192


@dataclass(frozen=True)
class ProbePlan:
    """Parameters of the index; a Gaussian projection of a unit vector has deviation 1, in which ``width`` is measured."""

    tables: int = 4
    projections: int = 4
    width: float = 1.6
    probes: int = 20
    seed: int = 11


def valid_vectors(df: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    """(id, vec) in doubles of the vectors that take part."""
    vec = F.col(vec_col).cast("array<double>")
    fine = F.forall(vec, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    rows = df.select(F.col(id_col).cast("long").alias("id"), vec.alias("vec")).where(F.col("id").isNotNull() & F.col("vec").isNotNull())
    return rows.where(fine & F.exists("vec", lambda x: x != 0))


def _projections(plan: ProbePlan, dim: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(plan.seed)
    a = rng.standard_normal((plan.tables, plan.projections, dim))
    return a, rng.random((plan.tables, plan.projections)) * plan.width


def _cells(plan: ProbePlan, unit: np.ndarray) -> np.ndarray:
    """Real-valued cell coordinates: (table, row, projection)."""
    a, b = _projections(plan, unit.shape[1])
    return (np.einsum("tpd,nd->tnp", a, unit) + b[:, None, :]) / plan.width


def _key(table: int, cell: np.ndarray) -> np.ndarray:
    """One long per cell: coordinates in 12 bits each, folded after the fifth."""
    out = np.full(len(cell), table, np.int64)
    for j in range(cell.shape[1]):
        out = out * np.int64(4099) + cell[:, j].astype(np.int64)
    return out


def probe_sequence(offset: np.ndarray, probes: int) -> np.ndarray:
    """(query, probe, projection) steps of -1, 0 or 1, best first by the squared distance to the crossed boundaries.

    ``offset`` is the position inside the own cell, 0 to 1. The template of expected order, over at most three crossings of the
    nearest boundaries, is shared by all queries; every query maps it on its own order of boundaries.
    """
    n, p = offset.shape
    dist = np.concatenate([offset, 1 - offset], 1)
    order = np.argsort(dist, 1, kind="stable")
    rank = np.arange(1, 2 * p + 1)
    expected = rank * (rank + 1) / (4 * (p + 1) * (p + 2))
    expected[p:] = (1 - (2 * p + 1 - rank[p:]) / (p + 1) + (2 * p + 1 - rank[p:]) * (2 * p + 2 - rank[p:]) / (4 * (p + 1) * (p + 2)))
    sets = [s for k in range(1, 4) for s in combinations(range(2 * p), k) if not any(2 * p - 1 - x in s for x in s)]
    sets = sorted(sets, key=lambda s: (expected[list(s)].sum(), s))[: probes - 1]
    steps = np.zeros((n, len(sets) + 1, p), np.int64)
    rows = np.arange(n)
    for i, s in enumerate(sets):
        for x in s:
            which = order[:, x]
            steps[rows, i + 1, which % p] = np.where(which < p, -1, 1)
    return steps


def _unit(column) -> np.ndarray:
    v = np.stack(column)
    v = v / np.abs(v).max(1, keepdims=True)
    return v / np.linalg.norm(v, axis=1, keepdims=True)


def _by_dim(batch: pa.RecordBatch):
    """(ids, vectors) of each vector length in a batch."""
    lens = batch.column(1).value_lengths().to_numpy(zero_copy_only=False)
    for d in np.unique(lens):
        part = batch.filter(pa.array(lens == d))
        yield part.column(0).to_numpy(), part.column(1).flatten().to_numpy(zero_copy_only=False).reshape(-1, int(d))


def _index_rows(plan: ProbePlan):
    def run(batches):
        for batch in batches:
            for ids, vec in _by_dim(batch):
                cells = np.floor(_cells(plan, _unit(vec)))
                key = np.concatenate([_key(t, c) for t, c in enumerate(cells)])
                yield pa.RecordBatch.from_arrays([pa.array(key), pa.array(np.tile(ids, plan.tables))], names=["cell", "id"])

    return run


def _probe_rows(plan: ProbePlan):
    def run(batches):
        for batch in batches:
            for ids, vec in _by_dim(batch):
                where = _cells(plan, _unit(vec))
                for t, c in enumerate(where):
                    home = np.floor(c)
                    steps = probe_sequence(c - home, plan.probes)
                    for i in range(steps.shape[1]):
                        yield pa.RecordBatch.from_arrays([pa.array(_key(t, home + steps[:, i])), pa.array(ids)], names=["cell", "id"])

    return run


def pair_cosine(q: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Cosine of each row of ``q`` with the same row of ``c``; the same two vectors give the same bits in any block."""
    return (q * c).sum(1) / (np.sqrt((q * q).sum(1)) * np.sqrt((c * c).sum(1)))


def best_of_block(query_ids, q, ids, c, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For each query its ``k`` best ids of a block (ties to smaller ids), its own id left out.

    A matrix product finds all pairs that may be among them; their scores are then computed pair by pair.
    """
    score = (q @ c.T) / (np.linalg.norm(q, axis=1)[:, None] * np.linalg.norm(c, axis=1)[None])
    own = query_ids[:, None] == ids[None]
    score[own] = -2.0
    rows = k * int(np.unique(ids, return_counts=True)[1].max())
    bar = np.partition(score, -rows, 1)[:, -rows] if len(ids) > rows else np.full(len(q), -2.0)
    r, j = np.nonzero((score >= bar[:, None] - 1e-9) & ~own)
    s = pair_cosine(q[r], c[j])
    o = np.lexsort((ids[j], -s, r))
    r, j, s = r[o], j[o], s[o]
    if rows > k:
        first = np.sort(np.unique(np.stack([r, ids[j]]), axis=1, return_index=True)[1])
        r, j, s = r[first], j[first], s[first]
    place = np.arange(len(r)) - np.searchsorted(r, r)
    keep = place < k
    return query_ids[r[keep]], ids[j[keep]], s[keep]


def _search_block(k: int):
    def run(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        out = []
        for d in left.vec.map(len).unique():
            q, c = left[left.vec.map(len) == d], right[right.vec.map(len) == d]
            if not len(c):
                continue
            ids, cv = c.id.to_numpy(), np.stack(c.vec)
            for i in range(0, len(q), 512):
                out.append(best_of_block(q.id.to_numpy()[i : i + 512], np.stack(q.vec[i : i + 512]), ids, cv, k))
        parts = [np.concatenate(x) for x in zip(*out)] if out else [np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)]
        return pd.DataFrame({"query_id": parts[0], "vec_id": parts[1], "score": parts[2]})

    return run


def nearest(vectors: DataFrame, queries: DataFrame, k: int = 5, plan: ProbePlan = ProbePlan()) -> DataFrame:
    """(query_id, rank, vec_id, score): for each query row ``(id, vec)`` its ``k`` nearest of ``vectors`` (id, vec) found."""
    ship_package(vectors.sparkSession)
    index = vectors.select("id", "vec").mapInArrow(_index_rows(plan), "cell long, id long")
    crowd = index.groupBy("cell").agg(F.ceil(F.count("*") / CELL_ROWS).alias("salts"))
    probes = queries.select("id", "vec").mapInArrow(_probe_rows(plan), "cell long, id long").distinct()
    met = probes.select("cell").distinct().join(crowd, "cell")
    dealt = index.join(met, "cell").withColumn("salt", F.pmod(F.xxhash64("id", "cell"), F.col("salts"))).select("cell", "salt", "id").join(vectors.select("id", "vec"), "id")
    asked = probes.join(met, "cell").withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.col("salts") - 1)))
    asked = asked.select("cell", "salt", "id").join(queries.select("id", "vec"), "id")
    found = asked.groupBy("cell", "salt").cogroup(dealt.groupBy("cell", "salt")).applyInPandas(_search_block(k), "query_id long, vec_id long, score double")
    found = staged(_best(found, k), "found")
    full = found.groupBy("query_id").count().where(F.col("count") >= k).select(F.col("query_id").alias("id"))
    short = staged(queries.select("id", "vec").join(full, "id", "left_anti"), "short")
    if not short.isEmpty():
        found = _best(found.drop("rank").unionByName(_exact(vectors, short, k)), k)
    return found.select("query_id", "rank", "vec_id", "score")


def _best(found: DataFrame, k: int) -> DataFrame:
    best = found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    return best.withColumn("rank", F.row_number().over(W.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id"))).where(F.col("rank") <= k)


def _exact(vectors: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """(query_id, vec_id, score) of the best of every block, each block of rows against each slice of the queries of their length."""
    dim = F.size("vec").alias("dim")
    parts = lambda df, name: df.groupBy(dim).agg(F.ceil(F.count("*") / CELL_ROWS).alias(name))
    grid = parts(queries, "slices").join(parts(vectors, "blocks"), "dim")
    deal = lambda n: F.pmod(F.xxhash64("id", "vec"), F.col(n))
    every = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), F.col(n) - 1))
    ours = vectors.select("id", "vec", dim).join(grid, "dim").select("id", "vec", "dim", deal("blocks").alias("block"), every("slices").alias("slice"))
    asked = queries.select("id", "vec", dim).join(grid, "dim").select("id", "vec", "dim", deal("slices").alias("slice"), every("blocks").alias("block"))
    keys = ("dim", "block", "slice")
    return asked.groupBy(*keys).cogroup(ours.groupBy(*keys)).applyInPandas(_search_block(k), "query_id long, vec_id long, score double")
