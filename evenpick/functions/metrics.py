"""Metrics in three equivalent forms: unrolled SQL expression, higher-order Column, NumPy block.

Rankings are encoded once as 0/1 vectors over item pairs; their number of inverted pairs is then the l1 distance of the encodings.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass
from itertools import combinations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from evenpick.functions.packed import PackedRows, whole_l1

#: Above this many terms an unrolled expression would leave the code generator; block kernels take over.
UNROLL_TERMS = 400


@dataclass(frozen=True)
class Metric:
    """``block(X, C)`` gives the distances of all rows of X to all rows of C; X may be packed."""

    name: str
    term: Callable[[Column, Column], Column]
    gather: Callable[[list[Column]], Column]
    fold: Callable[[Column], Column]
    block: Callable[[np.ndarray, np.ndarray], np.ndarray]

    def __reduce__(self):
        return metric, (self.name,)

    def to_point(self, vec: Column, point: Sequence[float]) -> Column:
        """Distance of a vector column to a constant point, unrolled for the code generator."""
        return self.gather([self.term(F.get(vec, i), F.lit(float(x))) for i, x in enumerate(point)])

    def between(self, a: Column, b: Column) -> Column:
        """Distance of two vector columns by higher-order functions (not for hot paths)."""
        return self.fold(F.zip_with(a, b, self.term))

    def one_to_many(self, x: np.ndarray, rows: np.ndarray) -> np.ndarray:
        return self.block(rows, x[None])[:, 0]


def _sum(parts: list[Column]) -> Column:
    out = parts[0]
    for p in parts[1:]:
        out = out + p
    return out


def _total(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, x: s + x)


def _blockwise(one: Callable[[np.ndarray], np.ndarray]) -> Callable[[np.ndarray, np.ndarray], np.ndarray]:
    """Distances row by row of the smaller side: memory stays at one copy of the other, and sums run in feature order."""

    def run(x: np.ndarray, c: np.ndarray) -> np.ndarray:
        out = np.empty((len(x), len(c)))
        if len(x) < len(c):
            for i, row in enumerate(x):
                out[i] = one(c - row)
            return out
        for j, center in enumerate(c):
            out[:, j] = one(x - center)
        return out

    return run


def _l1(d: np.ndarray) -> np.ndarray:
    if d.shape[1] > 64:
        return np.abs(d).sum(1)
    out = np.abs(d[:, 0]) if d.shape[1] else np.zeros(len(d))
    for j in range(1, d.shape[1]):
        out = out + np.abs(d[:, j])
    return out


def _l1_block(x: np.ndarray, c: np.ndarray, cells: int = 65_536) -> np.ndarray:
    """As ``_blockwise(_l1)``, feature by feature over tiles that stay in the cache; the sums have the same order."""
    dim = x.shape[1]
    if not 0 < dim <= 64 or min(len(x), len(c)) < 4:
        return _few_l1(x, c) if 0 < dim <= 64 and len(c) < 4 <= len(x) else _rows_l1(x, c)
    out, ct, step = np.empty((len(x), len(c))), np.ascontiguousarray(c.T), max(1, cells // len(c))
    room = np.empty((min(step, len(x)), len(c)))
    for i in range(0, len(x), step):
        part, to = x[i : i + step], out[i : i + step]
        gap = room[: len(part)]
        np.abs(np.subtract(part[:, :1], ct[0], out=to), out=to)
        for j in range(1, dim):
            np.abs(np.subtract(part[:, j : j + 1], ct[j], out=gap), out=gap)
            to += gap
    return out


_rows_l1 = _blockwise(_l1)


def _few_l1(x: np.ndarray, c: np.ndarray, rows: int = 512) -> np.ndarray:
    """As ``_rows_l1`` for few centers: blocks of rows are turned so that features are added up along contiguous rows, in the same order."""
    out, room = np.empty((len(x), len(c))), np.empty((x.shape[1], rows))
    for i in range(0, len(x), rows):
        part = x[i : i + rows].T
        gap = room[:, : part.shape[1]]
        for j, center in enumerate(c):
            np.abs(np.subtract(part, center[:, None], out=gap), out=gap)
            out[i : i + rows, j] = np.add.reduce(gap, axis=0)
    return out


def _jaccard_block(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    x, c = x != 0, c != 0
    both = x.astype(float) @ c.astype(float).T
    either = x.sum(1)[:, None] + c.sum(1)[None] - both
    return 1 - np.divide(both, either, out=np.ones_like(both), where=either > 0)


def _angular_block(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    n = np.linalg.norm(x, axis=1)[:, None] * np.linalg.norm(c, axis=1)[None]
    return np.arccos(np.clip(np.divide(x @ c.T, n, out=np.zeros((len(x), len(c))), where=n > 0), -1, 1)) / np.pi


def _jaccard_columns(parts: list[Column]) -> Column:
    return F.coalesce(1 - _sum([p["both"] for p in parts]) / F.nullif(_sum([p["either"] for p in parts]), F.lit(0.0)), F.lit(0.0))


def _pair_term(a: Column, b: Column) -> Column:
    return F.struct(((a != 0) & (b != 0)).cast("double").alias("both"), ((a != 0) | (b != 0)).cast("double").alias("either"))


def _jaccard_fold(a: Column) -> Column:
    both, either = _total(F.transform(a, lambda p: p["both"])), _total(F.transform(a, lambda p: p["either"]))
    return F.when(either == 0, F.lit(0.0)).otherwise(1 - both / either)


def _angle(dot: Column, aa: Column, bb: Column) -> Column:
    return F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), F.when(aa * bb > 0, dot / F.sqrt(aa * bb)).otherwise(0.0)))) / F.lit(float(np.pi))


_PRODUCTS = ("ab", "aa", "bb")


def _product_term(a: Column, b: Column) -> Column:
    return F.struct((a * b).alias("ab"), (a * a).alias("aa"), (b * b).alias("bb"))


def _any_rows(block: Callable, packed: Callable = lambda x, c: None) -> Callable[[np.ndarray | PackedRows, np.ndarray], np.ndarray]:
    """``block`` for packed rows too: by ``packed`` where it has an answer, else made dense block by block."""

    def run(x: np.ndarray | PackedRows, c: np.ndarray) -> np.ndarray:
        if not isinstance(x, PackedRows):
            return block(x, c)
        got = packed(x, c) if len(x) else np.zeros((0, len(c)))
        return np.concatenate([block(part, c) for part in x.dense_blocks()]) if got is None else got

    return run


METRICS: dict[str, Metric] = {
    m.name: m
    for m in (
        Metric("l1", lambda a, b: F.abs(a - b), _sum, _total, _any_rows(_l1_block, whole_l1)),
        Metric("inversions", lambda a, b: F.abs(a - b), _sum, _total, _any_rows(_l1_block, whole_l1)),
        Metric("l2", lambda a, b: (a - b) * (a - b), lambda p: F.sqrt(_sum(p)), lambda a: F.sqrt(_total(a)), _any_rows(_blockwise(lambda d: np.sqrt((d * d).sum(1))))),
        Metric("linf", lambda a, b: F.abs(a - b), lambda p: F.greatest(*p) if len(p) > 1 else p[0], F.array_max, _any_rows(_blockwise(lambda d: np.abs(d).max(1)))),
        Metric("hamming", lambda a, b: (a != b).cast("double"), _sum, _total, _any_rows(_blockwise(lambda d: (d != 0).sum(1).astype(float)))),
        Metric("jaccard", _pair_term, _jaccard_columns, _jaccard_fold, _any_rows(_jaccard_block)),
        Metric(
            "angular",
            _product_term,
            lambda p: _angle(*(_sum([x[k] for x in p]) for k in _PRODUCTS)),
            lambda a: _angle(*(_total(F.transform(a, lambda x, k=k: x[k])) for k in _PRODUCTS)),
            _any_rows(_angular_block),
        ),
    )
}


def metric(name: str | Metric) -> Metric:
    return name if isinstance(name, Metric) else METRICS[name]


def encode_ranking(positions: Sequence[Column]) -> Column:
    """Pair-sign encoding of a ranking given as the position of each item: 1 where the earlier item stands later."""
    return F.array(*[(positions[i] > positions[j]).cast("double") for i, j in combinations(range(len(positions)), 2)])
