"""Exact top-k inner products by a dual cover-tree search.

Queries and rows are dealt into blocks, and every block gets one cover tree, built once and stored. A query group's tree then meets the trees of all
blocks of rows: a pair of nodes is dropped when the largest inner product that their centers and covering radii allow is below the
worst kth score of the query node. The first block a group meets gives its queries kth scores, and they are carried to all others.

Vectors are integers floor(64 x), so scores are exact. Defined results: vectors that are null or hold null or non-finite components take no part
(zero vectors do); only vectors of one length are compared; a query's own id is no candidate; equal scores go to the smaller id;
fewer candidates than k are all returned; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import pickle

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from evenpick.plans.durable import ship_package, staged

BLOCK_ROWS, BLOCK_QUERIES = 8192, 2048
#: Points up to which a node of rows, and of queries, is a leaf; one with more is a leaf, too, where balls of half its radius hold fewer than SHARE points on average (of
#: PROBE of its points, then of all): such a split tells nothing.
LEAF, QUERY_LEAF, SHARE, PROBE = 64, 4, 2, 128


def integer_vectors(df: DataFrame, id_col: str, vec_col: str, scale: int = 64) -> DataFrame:
    """(id, vec) with components floor(scale * x) of the vectors that take part."""
    vec = F.col(vec_col).cast("array<double>")
    fine = F.forall(vec, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    rows = df.select(F.col(id_col).cast("long").alias("id"), vec.alias("vec")).where(F.col("id").isNotNull() & F.col("vec").isNotNull())
    return rows.where(fine).select("id", F.transform("vec", lambda x: F.floor(x * scale)).alias("vec"))


class CoverNode:
    """A ball of radius 2^level around a center that covers its points, with children of level - 1 or, as a leaf, the points themselves.

    Children's centers are points of the node, the node's own first, and more than 2^(level - 1) apart; each covers the points nearest to it.
    ``radius`` is the distance of the farthest point covered.
    """

    __slots__ = ("center", "level", "radius", "norm", "rows", "children", "centers", "radii", "norms", "worst")

    def __init__(self, x: np.ndarray, rows: np.ndarray, center: int, dist: np.ndarray, leaf: int = LEAF):
        self.center, self.rows = x[center], rows
        self.radius = float(dist.max()) * (1 + 1e-12) if len(dist) else 0.0
        self.level = int(np.ceil(np.log2(self.radius))) if self.radius > 0 else None
        self.norm, self.worst = float(np.linalg.norm(self.center)), -np.inf
        self.children: list[CoverNode] = []
        if len(rows) > leaf and self.radius > 0:
            self._split(x, center, leaf)

    def _split(self, x: np.ndarray, center: int, leaf: int) -> None:
        half, points = 2.0 ** (self.level - 1), x[self.rows]
        at = int(np.flatnonzero(self.rows == center)[0])
        if _balls(points[:: max(1, len(points) // PROBE)], 0, half) is None or (got := _balls(points, at, half)) is None:
            return
        chosen, owner, near = got
        self.children = [CoverNode(x, self.rows[owner == i], int(self.rows[c]), near[owner == i], leaf) for i, c in enumerate(chosen)]
        self.centers = np.stack([n.center for n in self.children])
        self.radii = np.array([n.radius for n in self.children])
        self.norms = np.array([n.norm for n in self.children])


def _balls(points: np.ndarray, at: int, radius: float):
    """(centers, owner, distance) of a farthest-first cover by balls, or None if they hold fewer than ``SHARE`` points on average."""
    near, owner, chosen = np.full(len(points), np.inf), np.zeros(len(points), np.int64), []
    while near.max() > radius:
        if (len(chosen) + 1) * SHARE > len(points):
            return None
        d = np.sqrt(np.einsum("ij,ij->i", points - points[at], points - points[at]))
        closer = d < near
        near[closer], owner[closer] = d[closer], len(chosen)
        chosen.append(at)
        at = int(near.argmax())
    return chosen, owner, near


def cover_tree(x: np.ndarray, leaf: int = LEAF) -> CoverNode:
    return CoverNode(x, np.arange(len(x)), 0, np.linalg.norm(x - x[0], axis=1), leaf)


class DualSearch:
    """All queries of a group against all rows of a block; ``floor`` holds scores that a query's kth is known to reach."""

    def __init__(self, query_ids, queries, ids, rows, k: int, trees: tuple[CoverNode, CoverNode] | None = None, floor: np.ndarray | None = None):
        self.k, self.query_ids, self.ids = k, query_ids, ids
        big = float(np.abs(queries).max(initial=0)) * float(np.abs(rows).max(initial=0)) * queries.shape[1]
        exact = np.float64 if big < 2**53 else np.int64 if big < 2**63 else object
        self.q, self.x = queries.astype(exact), rows.astype(exact)
        self.slack = 1e-9 * (1 + big)
        self.score = np.full((len(queries), k), -np.inf if exact is np.float64 else -(2**63) + 1, exact if exact is not object else object)
        self.found = np.full((len(queries), k), np.iinfo(np.int64).max)
        self.floor = np.full(len(queries), self.score[0, 0] if len(queries) else 0, self.score.dtype) if floor is None else floor.astype(self.score.dtype)
        self.pruned = self.compared = 0
        if len(queries) and len(rows):
            a, b = trees or (cover_tree(queries.astype(np.float64), QUERY_LEAF), cover_tree(rows.astype(np.float64)))
            self._start(a)
            self._visit(a, b)

    def _start(self, a: CoverNode) -> None:
        for child in a.children:
            self._start(child)
        a.worst = float(self.floor[a.rows].min())

    def _bound(self, a: CoverNode, centers, radii, norms):
        return centers @ a.center + a.norm * radii + norms * a.radius + a.radius * radii + self.slack

    def _visit(self, a: CoverNode, b: CoverNode) -> None:
        if a.children and (not b.children or a.radius >= b.radius or len(a.rows) > len(b.rows)):
            for child in a.children:
                if self._bound(child, b.center, b.radius, b.norm) >= child.worst:
                    self._visit(child, b)
                else:
                    self.pruned += len(child.rows) * len(b.rows)
            a.worst = min(c.worst for c in a.children)
        elif b.children:
            bounds = self._bound(a, b.centers, b.radii, b.norms)
            for i in np.argsort(-bounds, kind="stable"):
                if bounds[i] >= a.worst:
                    self._visit(a, b.children[i])
                else:
                    self.pruned += len(a.rows) * len(b.children[i].rows)
        else:
            self._compare(a, b)

    def _compare(self, a: CoverNode, b: CoverNode) -> None:
        self.compared += len(a.rows) * len(b.rows)
        s = self.q[a.rows] @ self.x[b.rows].T
        ids = self.ids[b.rows]
        kth = np.maximum(self.score[a.rows, -1], self.floor[a.rows])
        can = (s >= kth[:, None]) & (self.query_ids[a.rows][:, None] != ids[None])
        hit = np.flatnonzero(can.any(1))
        if len(hit):
            rows = a.rows[hit]
            cols = np.flatnonzero(can[hit].any(0))
            low = self.score.dtype.type(-np.inf) if self.score.dtype == np.float64 else -(2**63) + 1
            s = np.where(can[np.ix_(hit, cols)], s[np.ix_(hit, cols)], low)
            i = np.where(can[np.ix_(hit, cols)], ids[cols][None], np.iinfo(np.int64).max)
            score, found = np.concatenate([self.score[rows], s], 1), np.concatenate([self.found[rows], i], 1)
            order = np.lexsort((found, -score), axis=1)[:, : self.k] if score.dtype != object else np.array([sorted(range(score.shape[1]), key=lambda j: (-score[r, j], found[r, j]))[: self.k] for r in range(len(rows))])
            self.score[rows], self.found[rows] = np.take_along_axis(score, order, 1), np.take_along_axis(found, order, 1)
        a.worst = float(np.maximum(self.score[a.rows, -1], self.floor[a.rows]).min())

    def result(self) -> pd.DataFrame:
        r, j = np.nonzero(self.found != np.iinfo(np.int64).max)
        return pd.DataFrame({"query_id": self.query_ids[r], "vec_id": self.found[r, j], "score": self.score[r, j].astype(np.int64)})


def _trees(rows: DataFrame, blocks: int, seed: int, label: str, leaf: int) -> DataFrame:
    """(block, dim, tree): one stored cover tree, with its ids and vectors, per block and vector length."""
    dealt = rows.where(F.size("vec") > 0).select(F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(blocks)).alias("block"), F.size("vec").alias("dim"), "id", "vec")

    def build(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        x = np.stack(pdf.vec)
        blob = pickle.dumps((pdf.id.to_numpy(), x, cover_tree(x.astype(np.float64), leaf)))
        return pd.DataFrame({"block": [key[0]], "dim": [key[1]], "tree": [blob]})

    return staged(dealt.groupBy("block", "dim").applyInPandas(build, "block long, dim int, tree binary"), label)


def _search(k: int):
    def run(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        if not len(left) or not len(right):
            return pd.DataFrame({"query_id": np.zeros(0, np.int64), "vec_id": np.zeros(0, np.int64), "score": np.zeros(0, np.int64)})
        (query_ids, q, a), (ids, x, b) = pickle.loads(left.tree[0]), pickle.loads(right.tree[0])
        floor = None
        if left.floors[0] is not None and len(left.floors[0]):
            known = {f["id"]: f["kth"] for f in left.floors[0]}
            floor = np.array([known.get(i, -(2**63) + 1) for i in query_ids.tolist()], np.int64)
        return DualSearch(query_ids, q, ids, x, k, (a, b), floor).result()

    return run


def exact_top_k(rows: DataFrame, queries: DataFrame, k: int = 20, block_rows: int = BLOCK_ROWS, block_queries: int = BLOCK_QUERIES) -> DataFrame:
    """(query_id, rank, vec_id, score): for each query ``(id, vec)`` the ``k`` rows ``(id, vec)`` of largest inner product."""
    ship_package(rows.sparkSession)
    blocks, groups = (max(1, -(-df.count() // n)) for df, n in ((rows, block_rows), (queries, block_queries)))
    right = _trees(rows, blocks, 42, "row-trees", LEAF)
    left = _trees(queries, groups, 5, "query-trees", QUERY_LEAF).withColumnRenamed("block", "part")
    every = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long")))
    home = F.col("block") == F.pmod("part", F.lit(blocks))

    def met(floors: DataFrame, where) -> DataFrame:
        ours = left.join(floors, "part", "left").withColumn("block", every(blocks)).where(where)
        theirs = right.withColumn("part", every(groups)).where(where)
        pairs = ours.groupBy("part", "block", "dim").cogroup(theirs.groupBy("part", "block", "dim"))
        return pairs.applyInPandas(_search(k), "query_id long, vec_id long, score long")

    nothing = "array<struct<id: long, kth: long>>"
    found = staged(met(left.select("part").distinct().withColumn("floors", F.lit(None).cast(nothing)), home), "home-block")
    if blocks > 1:
        kth = found.groupBy("query_id").agg(F.min("score").alias("kth"), F.count("*").alias("n")).where(F.col("n") >= k)
        part = F.pmod(F.xxhash64("query_id", F.lit(5)), F.lit(groups)).alias("part")
        floors = kth.groupBy(part).agg(F.collect_list(F.struct(F.col("query_id").alias("id"), "kth")).cast(nothing).alias("floors"))
        found = found.unionByName(met(floors, ~home))
    best = found.withColumn("rank", F.row_number().over(W.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")))
    return best.where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
