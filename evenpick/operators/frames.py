"""Between frames and kernels: schemas, conversions, and grouped or streaming runs of a kernel."""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import _parse_datatype_string

from evenpick.functions.kernels import Net
from evenpick.functions.packed import BLOCK_VALUES, PackedRows, pack, unpack
from evenpick.plans.durable import ship_package, staged, swept

REPS = "array<struct<grp: int, point_id: long, vec: array<double>, dist: double>>"
NET = f"net_id long, vec array<double>, grp int, groups long, reps {REPS}"
SUMMARY = f"shard long, r_t double, n_t long, {NET}"
CENTER = "rank int, point_id long, grp int, vec array<double>"
#: Most groups whose bits fit one long.
MAX_GROUPS = 62
#: Vector components that a worker buffers per shard when the number of shards is left open (200 MB of doubles).
SHARD_VALUES = 25_000_000
#: Most rows that a solver takes to the driver.
DRIVER_ROWS = 2_000_000
#: Most vector components that a driver run takes (160 MB of doubles).
DRIVER_VALUES = 20_000_000


def fits_driver(rows: int, dim: int | None) -> bool:
    return rows <= DRIVER_ROWS and rows * (dim or 1) <= DRIVER_VALUES


def for_driver(points: DataFrame, groups: Sequence[str] = ("grp",)) -> tuple[DataFrame, bool]:
    """(points, whether they fit the driver). Where they do not, equal positions of a group (in all columns of ``groups``) become one point, that of the least id."""
    size = lambda df: fits_driver(*df.agg(F.count("*"), F.max(dimension(df))).first())
    if size(points):
        return points, True
    once = staged(points.groupBy(*groups, "vec").agg(F.min("point_id").alias("point_id")).select("point_id", *groups, "vec"), "positions")
    return once, size(once)


def packed(points: DataFrame) -> DataFrame:
    """Points whose ``vec`` is a binary of its nonzero components: what wide and mostly zero vectors are kept and read as.

    A reader that fills thousands of rows at once then holds kilobytes a row; kernels read packed rows, or dense blocks of bounded size.
    """
    ship_package(points.sparkSession)

    def run(batches):
        for b in batches:
            for i in range(0, b.num_rows, 256):
                part = b.slice(i, 256)
                vecs = pa.array([pack(v) for v in dense(part.column(2))], pa.binary())
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), vecs], names=["point_id", "grp", "vec"])

    return points.select("point_id", "grp", "vec").mapInArrow(run, "point_id long, grp int, vec binary")


def blocks(column, values: int = BLOCK_VALUES):
    """(rows, matrix) of a vector column: all at once, or packed vectors in blocks of at most ``values`` components."""
    if not len(column) or not isinstance(column[0], bytes):
        yield slice(0, len(column)), matrix(column)
        return
    step = max(1, values // max(1, int(np.frombuffer(column[0], np.int32, 1)[0])))
    for i in range(0, len(column), step):
        yield slice(i, i + step), matrix(column[i : i + step])


def matrix(column) -> np.ndarray:
    if len(column) and isinstance(column[0], bytes):
        return np.stack([unpack(v) for v in column])
    return np.stack(column).astype(float) if len(column) else np.zeros((0, 0))


def dimension(points: DataFrame) -> Column:
    """The size of ``vec``, packed or not."""
    if points.schema["vec"].dataType.typeName() != "binary":
        return F.size("vec")
    word = [F.conv(F.hex(F.substring("vec", i, 1)), 16, 10).cast("int") * 256 ** (i - 1) for i in range(1, 5)]
    return word[0] + word[1] + word[2] + word[3]


def dense(column: pa.ListArray | pa.ChunkedArray) -> np.ndarray:
    """The vectors of an Arrow column as one matrix, without an object per row."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    if not len(column):
        return np.zeros((0, 0))
    sizes = None if pa.types.is_binary(column.type) else column.value_lengths()
    if pa.types.is_binary(column.type):
        return matrix(column.to_numpy(zero_copy_only=False))
    if column.null_count or pc.min(sizes) != pc.max(sizes):
        raise ValueError("vectors must be present and of one length")
    return column.flatten().to_numpy(zero_copy_only=False).astype(float, copy=False).reshape(len(column), -1)


def point_arrays(points: DataFrame, limit: int = DRIVER_ROWS) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``arrays`` of points that fit the driver, through Arrow."""
    table = points.select("point_id", F.col("grp").cast("long"), "vec").limit(limit + 1).toArrow()
    if table.num_rows > limit:
        raise ValueError(f"more than {limit} rows for the driver")
    ids = table.column(0).to_numpy().astype(np.int64, copy=False)
    order = np.argsort(ids, kind="stable")
    return dense(table.column(2))[order], ids[order], table.column(1).to_numpy().astype(np.int64, copy=False)[order]


def arrays(pdf: pd.DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(vectors, ids, groups) ordered by id, so kernels break ties by the smaller id."""
    pdf = pdf.sort_values("point_id", kind="stable")
    vec = pdf.vec.to_numpy()
    return PackedRows.of(vec) if len(vec) and isinstance(vec[0], bytes) else matrix(vec), pdf.point_id.to_numpy(np.int64), pdf.grp.to_numpy(np.int64)


def net_rows(net: Net, **extra) -> pd.DataFrame:
    rows = [
        (*extra.values(), i, v.tolist(), g, sum(1 << k for k in r), [{"grp": k, "point_id": p, "vec": np.asarray(x).tolist(), "dist": float(d)} for k, (p, x, d) in sorted(r.items())])
        for i, v, g, r in zip(net.ids, net.vecs, net.grps, net.reps)
    ]
    return pd.DataFrame(rows, columns=[*extra, "net_id", "vec", "grp", "groups", "reps"])


def net_of(pdf: pd.DataFrame) -> Net:
    net = Net()
    for i, v, g, reps in zip(pdf.net_id, pdf.vec, pdf.grp, pdf.reps):
        net.add(i, np.asarray(v, float), g, {int(r["grp"]): (int(r["point_id"]), np.asarray(r["vec"], float), float(r["dist"])) for r in reps})
    return net


def whole_numbers(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    if column.null_count:
        raise ValueError("ids and groups must be present")
    return (column.to_numpy() if isinstance(column, pa.ChunkedArray) else column.to_numpy(zero_copy_only=False)).astype(np.int64, copy=False)


def rows_of(column: pa.Array | pa.ChunkedArray) -> np.ndarray | PackedRows:
    """The vectors of an Arrow column, packed where they are."""
    return PackedRows.of(column.to_numpy(zero_copy_only=False) if isinstance(column, pa.Array) else column.to_numpy()) if pa.types.is_binary(column.type) else dense(column)


def vector_blocks(column: pa.Array | pa.ChunkedArray, rows: int = 4096):
    """(rows, vectors) of an Arrow column, without an object per component; packed vectors stay packed."""
    if pa.types.is_binary(column.type):
        for i in range(0, len(column), rows):
            yield slice(i, i + rows), rows_of(column.slice(i, rows))
    else:
        yield slice(0, len(column)), dense(column)


def arrow_schema(schema: str) -> pa.Schema:
    return to_arrow_schema(_parse_datatype_string(schema))


def per_shard(points: DataFrame, run: Callable[[int, np.ndarray, np.ndarray, np.ndarray], pd.DataFrame], schema: str) -> DataFrame:
    """``run(shard, vectors, ids, groups)`` on every shard; the shards are dealt by one exchange."""
    ship_package(points.sparkSession)
    out = arrow_schema(schema)

    def work(key: tuple, t: pa.Table) -> pa.Table:
        ids = whole_numbers(t["point_id"])
        order = np.argsort(ids, kind="stable")  # kernels break ties by the smaller id
        vec = rows_of(t["vec"])[order]
        return pa.Table.from_pandas(run(key[0].as_py(), vec, ids[order], whole_numbers(t["grp"])[order]), out, preserve_index=False)

    return points.select("shard", "point_id", "grp", "vec").groupBy("shard").applyInArrow(work, schema)


def per_shard_stream(points: DataFrame, start: Callable, finish: Callable, schema: str) -> DataFrame:
    """One kernel per shard, fed block by block in id order: memory is the kernel's own, however large a shard is.

    ``start()`` makes a kernel with ``insert_block``; ``finish(shard, kernel)`` gives its rows.
    """
    ship_package(points.sparkSession)

    def work(batches):
        shard, kernel = None, None
        for b in batches:
            of = b.shard.to_numpy(np.int64)
            for part in np.split(np.arange(len(of)), np.flatnonzero(np.diff(of)) + 1):
                if not len(part):
                    continue
                if kernel is None or of[part[0]] != shard:
                    if kernel is not None:
                        yield finish(shard, kernel)
                    shard, kernel = int(of[part[0]]), start()
                rows = b.iloc[part]
                kernel.insert_block(matrix(rows.vec.to_numpy()), rows.point_id.to_numpy(np.int64), rows.grp.to_numpy(np.int64))
        if kernel is not None:
            yield finish(shard, kernel)

    return points.select("shard", "point_id", "grp", "vec").repartition("shard").sortWithinPartitions("shard", "point_id").mapInPandas(work, schema)


def in_order(points: DataFrame, order: list[Column | str], run: Callable[[Iterator[tuple]], Iterator[pd.DataFrame]], schema: str) -> DataFrame:
    """One ordered replay of all points through ``run`` (a stream is one task by definition); memory is the kernel's own."""
    ship_package(points.sparkSession)
    out = arrow_schema(schema)

    def work(batches):
        parts = ((x, whole_numbers(b.column(0))[at], whole_numbers(b.column(1))[at]) for b in batches if b.num_rows for at, x in vector_blocks(b.column(2)))
        for pdf in run(parts):
            yield from pa.Table.from_pandas(pdf, out, preserve_index=False).to_batches()

    return points.repartition(1).sortWithinPartitions(*order).select("point_id", "grp", "vec").mapInArrow(work, schema)


def to_driver(df: DataFrame, limit: int = DRIVER_ROWS) -> pd.DataFrame:
    """A summary as pandas; refuses what is no summary."""
    with swept(df.sparkSession):
        out = df.limit(limit + 1).toPandas()
    if len(out) > limit:
        raise ValueError(f"more than {limit} rows for the driver: use more merge levels or a smaller budget")
    return out


def centers_frame(spark: SparkSession, ids, grps, vecs) -> DataFrame:
    rows = [(i, int(p), int(g), [float(x) for x in v]) for i, (p, g, v) in enumerate(zip(ids, grps, vecs))]
    return spark.createDataFrame(rows, CENTER)


def shards_for(points: DataFrame, shards: int | None, values: int = SHARD_VALUES) -> int:
    """``shards`` as given, or (None) so many that a buffered shard holds at most ``values`` vector components."""
    if shards:
        return shards
    n, d = points.agg(F.count("*"), F.max(F.size("vec"))).first()
    return max(1, -(-n * (d or 1) // values))


def shard_points(points: DataFrame, shards: int, how: str = "hash") -> DataFrame:
    """A ``shard`` column: 'hash' of the id, or its 'modulo' (for references that cannot hash alike)."""
    key = F.xxhash64("point_id") if how == "hash" else F.col("point_id")
    return points.withColumn("shard", F.pmod(key, F.lit(shards)).cast("long"))
