"""The uniform set as a Python data source: batch partitions by id range, and a stream that hands out ids in order."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

BLOCK = 1024


def _rows(start: int, stop: int, dim: int, groups: int, scale: float, seed: int):
    """Ids are cut into fixed blocks with a generator each, so a row does not depend on how ranges are dealt."""
    for block in range(start // BLOCK, -(-stop // BLOCK)):
        rng = np.random.default_rng([seed, block])
        x, g = rng.random((BLOCK, dim)) * scale, rng.integers(0, groups, BLOCK)
        for i in range(max(start, block * BLOCK), min(stop, (block + 1) * BLOCK)):
            yield i, int(g[i % BLOCK]), x[i % BLOCK]


class _Range(InputPartition):
    def __init__(self, start: int, stop: int):
        self.start, self.stop = start, stop


class _Reader(DataSourceReader):
    def __init__(self, o: dict):
        self.o = o

    def partitions(self):
        n, parts = int(self.o.get("rows", 1000)), int(self.o.get("partitions", 8))
        step = -(-n // parts)
        return [_Range(i, min(n, i + step)) for i in range(0, n, step)]

    def read(self, partition):
        ids, grp, vec = zip(*_rows(partition.start, partition.stop, int(self.o.get("dim", 10)), int(self.o.get("groups", 4)), float(self.o.get("scale", 1e5)), int(self.o.get("seed", 7))))
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(grp, pa.int32()), pa.array([v.tolist() for v in vec], pa.list_(pa.float64()))], names=["point_id", "grp", "vec"])


class _Stream(SimpleDataSourceStreamReader):
    def __init__(self, o: dict):
        self.o = o

    def initialOffset(self):
        return {"at": 0}

    def read(self, start):
        a = int(start["at"])
        b = min(int(self.o.get("rows", 1000)), a + int(self.o.get("per_batch", 100)))
        return iter(self._between(a, b)), {"at": b}

    def readBetweenOffsets(self, start, end):
        return iter(self._between(int(start["at"]), int(end["at"])))

    def _between(self, a: int, b: int):
        rows = _rows(a, b, int(self.o.get("dim", 10)), int(self.o.get("groups", 4)), float(self.o.get("scale", 1e5)), int(self.o.get("seed", 7)))
        return [(i, g, v.tolist()) for i, g, v in rows] if b > a else []


class UniformPoints(DataSource):
    """``spark.read.format("uniform_points").option("rows", n).option("dim", d)``; options: rows, dim, groups, scale, seed, partitions, per_batch."""

    @classmethod
    def name(cls):
        return "uniform_points"

    def schema(self):
        return "point_id long, grp int, vec array<double>"

    def reader(self, schema):
        return _Reader(self.options)

    def simpleStreamReader(self, schema):
        return _Stream(self.options)
