"""Points ``(point_id bigint, grp int, vec array<double>)`` from the given tables, and the generators of the uniform set.

Features stay flat columns until the last projection, so the Parquet scan reads only what a workload needs.
"""

from __future__ import annotations

import math
from collections.abc import Sequence
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from evenpick.functions.metrics import encode_ranking
from evenpick.functions.packed import packed_sums
from evenpick.plans.durable import drop_staged, ship_package, shuffle_width, staged

POINT = "point_id long, grp int, vec array<double>"
RANKED_BRANDS = 10


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_points(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """Points from Parquet, ORC or JSON (``vec`` as an array) or CSV (``vec`` as numbers separated by spaces)."""
    if fmt == "csv":
        raw = spark.read.schema("point_id long, grp int, vec string").csv(path, header=True)
        return raw.withColumn("vec", F.split("vec", " ").cast("array<double>"))
    return spark.read.schema(POINT).format(fmt).load(path)


def write_points(points: DataFrame, path: str, fmt: str = "parquet", mode: str = "error") -> None:
    if fmt == "csv":
        points = points.withColumn("vec", F.array_join(F.transform("vec", lambda x: x.cast("string")), " "))
        points.write.mode(mode).csv(path, header=True)
    else:
        points.write.mode(mode).format(fmt).save(path)


def validated(points: DataFrame, dim: int, groups: int, on_bad: str = "error") -> DataFrame:
    """Points checked row by row: id and group present and in domain, ``dim`` finite components. 'drop' filters, 'error' raises at run time."""
    fine = F.forall("vec", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    ok = F.coalesce(F.col("point_id").isNotNull() & F.col("grp").between(0, groups - 1) & (F.size("vec") == dim) & fine, F.lit(False))
    if on_bad == "drop":
        return points.where(ok)
    return points.where(F.when(ok, True).otherwise(F.raise_error(F.concat(F.lit("invalid point "), F.coalesce(F.col("point_id").cast("string"), F.lit("null")))).cast("boolean")))


def points_from(df: DataFrame, point_id: Column | str, features: Sequence[Column | str], group: Column | str) -> DataFrame:
    col = lambda c: F.col(c) if isinstance(c, str) else c
    return df.select(col(point_id).cast("long").alias("point_id"), col(group).cast("int").alias("grp"), F.array(*[col(f).cast("double") for f in features]).alias("vec"))


def points_by_all(df: DataFrame, point_id: Column | str, vec: Column, groups: dict[int, Column]) -> DataFrame:
    """Points with a group column ``g<n>`` for each number of groups, so that one build serves all of them."""
    return df.select(F.col(point_id).alias("point_id"), *[c.cast("int").alias(f"g{n}") for n, c in groups.items()], vec.alias("vec"))


def of_groups(points: DataFrame, groups: int) -> DataFrame:
    return points.select("point_id", F.col(f"g{groups}").alias("grp"), "vec")


def with_group(df: DataFrame, column: str, into: str = "grp") -> DataFrame:
    """Dense group numbers by sorted distinct value. The dictionary has one row per group and is joined, not windowed over the data."""
    names = df.select(column).distinct().withColumn(into, F.row_number().over(W.orderBy(column)) - 1)
    return df.join(F.broadcast(names), column)


def crossed(a: str, b: str, n_b: int) -> Column:
    return F.col(a) * n_b + F.col(b)


def _half_down(total, n: int, digits: int) -> float:
    """``total / n`` to ``digits`` decimals in exact arithmetic; an exact tie goes towards zero."""
    scaled = abs(Fraction(total)) * 10**digits / n
    return math.copysign(math.ceil(scaled - Fraction(1, 2)) / 10**digits, total)


def normalise(df: DataFrame, columns: Sequence[str], kind: str = "zscore", digits: int = 6) -> DataFrame:
    """Columns scaled by one aggregate over the table: population z-scores or the 0..1 range; a constant column becomes 0.

    Mean and deviation are rounded to ``digits`` decimals, so the order in which tasks add up does not show in the points. Means of decimal
    values often end in a tie there, which a sum of doubles would break either way: they are added up as decimals.
    """
    if kind == "none":
        return df
    if kind == "zscore":
        return df.withColumns(zscores(df, columns, digits))
    stats = [x for c in columns for x in (F.min(c).alias(f"{c}__a"), (F.max(c) - F.min(c)).alias(f"{c}__b"))]
    one = df.agg(*stats)
    out = df.crossJoin(F.broadcast(one))
    scaled = {c: F.when(F.col(f"{c}__b") > 0, (F.col(c) - F.col(f"{c}__a")) / F.col(f"{c}__b")).otherwise(0.0) for c in columns}
    return out.withColumns(scaled).drop(*one.columns)


def zscores(df: DataFrame, columns: Sequence[str], digits: int = 6) -> dict[str, Column]:
    """The population z-scores of ``normalise`` as expressions, so that rows can be moved and kept with their plain values."""
    exact = lambda c: F.col(c).cast("double").try_cast("decimal(28, 12)")
    one = df.agg(*[F.struct(F.count(c).alias("n"), F.count(exact(c)).alias("held"), F.sum(exact(c)).alias("total"), F.round(F.avg(c), digits).alias("mean"), F.round(F.stddev_pop(c), digits).alias("dev")).alias(c) for c in columns]).first()
    mean = {c: _half_down(one[c].total, one[c].n, digits) if one[c].total is not None and one[c].held == one[c].n else one[c].mean for c in columns}
    return {c: (F.col(c) - mean[c]) / one[c].dev if one[c].dev and one[c].dev > 0 else F.lit(0.0) for c in columns}


def dense_ids(df: DataFrame, order: Sequence[Column | str], into: str = "point_id", keep: Sequence[str] | None = None) -> DataFrame:
    """Row numbers 0.. in a total order without a one-task window: range-partitioned sort, then per-partition offsets. ``keep``: the columns wanted besides."""
    n = shuffle_width(df.sparkSession)
    part = df.repartitionByRange(n, *order).sortWithinPartitions(*order).select(*(keep or df.columns))
    part = staged(part.withColumn("__slot", F.monotonically_increasing_id()), "ordered")
    slot, place = F.shiftright("__slot", 33), F.col("__slot").bitwiseAND(F.lit((1 << 33) - 1))
    counts = part.groupBy(slot.alias("__part")).agg(F.count("*").alias("__n"))
    before = F.coalesce(F.sum("__n").over(W.orderBy("__part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    offsets = F.broadcast(counts.select("__part", before.alias("__before")))
    return part.withColumn("__part", slot).join(offsets, "__part").withColumn(into, F.col("__before") + place).drop("__slot", "__part", "__before")


def select_groups(points: DataFrame, groups: Sequence[int]) -> DataFrame:
    """Points of some groups."""
    return points.where(F.col("grp").isin(list(groups)))


def dedupe_points(points: DataFrame) -> DataFrame:
    """One point, that of the least id, for equal positions of one group."""
    return points.groupBy("grp", "vec").agg(F.min("point_id").alias("point_id")).select("point_id", "grp", "vec")


def head(points: DataFrame, n: int) -> DataFrame:
    """The first ``n`` points by id (the small-data workload)."""
    return points.orderBy("point_id").limit(n)


def cust2d(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = with_group(load(spark, sf_dir, "customer").select("c_custkey", "c_acctbal", "c_nationkey", "c_mktsegment"), "c_mktsegment")
    return points_from(c, "c_custkey", [F.col("c_acctbal") / 1000, F.lit(0.4).cast("double") * F.col("c_nationkey")], "grp")


def corr4(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers whose groups are ranges of their balance, so capacities bind. Cut points are quartiles, found without a global window."""
    c = load(spark, sf_dir, "customer").select("c_custkey", "c_acctbal", "c_nationkey")
    q = c.agg(F.percentile("c_acctbal", F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75))).alias("q"))
    grp = F.aggregate("q", F.lit(0), lambda s, x: s + (F.col("c_acctbal") >= x).cast("int"))
    return points_from(c.crossJoin(F.broadcast(q)), "c_custkey", [F.col("c_acctbal") / 1000, F.lit(0.4) * F.col("c_nationkey")], grp)


def day_number(c: str) -> Column:
    return F.datediff(F.col(c).cast("date"), F.lit("1970-01-01").cast("date"))


def ord2d(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = load(spark, sf_dir, "orders").select("o_orderkey", F.col("o_totalprice").alias("price"), day_number("o_orderdate").alias("day"), "o_orderstatus")
    return points_from(with_group(normalise(o, ["price", "day"]), "o_orderstatus"), "o_orderkey", ["price", "day"], "grp")


LINE_FEATURES = ("quantity", "price", "discount", "tax", "ship_day", "total")


def line_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line items with their orders: plain features, both group attributes, arrival order columns; joined once and written."""
    l = load(spark, sf_dir, "lineitem").select(
        "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_linestatus", F.col("l_quantity").alias("quantity"), F.col("l_extendedprice").alias("price"),
        F.col("l_discount").alias("discount"), F.col("l_tax").alias("tax"), day_number("l_shipdate").cast("double").alias("ship_day"),
    )
    o = load(spark, sf_dir, "orders").select("o_orderkey", "o_orderdate", F.col("o_totalprice").alias("total"), "o_orderpriority")
    return staged(l.join(o, l.l_orderkey == o.o_orderkey).drop("o_orderkey"), "line-rows")


def line6(spark: SparkSession, sf_dir: str, groups: int = 2) -> DataFrame:
    """Stand-in for the census set: six z-scored features; groups 2 (line status), 5 (order priority) or 10 (crossed). Ids follow arrival order."""
    return of_groups(line6_by_all(spark, sf_dir, (groups,)), groups)


def line6_by_all(spark: SparkSession, sf_dir: str, groups: Sequence[int] = (2, 5, 10)) -> DataFrame:
    lines = line_rows(spark, sf_dir)
    score = zscores(lines, LINE_FEATURES)
    named = with_group(with_group(lines, "l_linestatus", "status"), "o_orderpriority", "priority").drop("l_linestatus", "o_orderpriority")
    order = ["o_orderdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "price", score["discount"], score["tax"], score["ship_day"]]
    rows = dense_ids(named, order, keep=[*LINE_FEATURES, "status", "priority"])
    drop_staged(lines)
    grp = {2: F.col("status"), 5: F.col("priority"), 10: crossed("status", "priority", 5)}
    return points_by_all(rows, "point_id", F.array(*[score[f].cast("double") for f in LINE_FEATURES]), {g: grp[g] for g in groups})


def line4(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four z-scored line item features, return flag x line status groups; ids hash all identifying columns (no order needed)."""
    l = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus")
    l = l.withColumn("id", F.xxhash64("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax"))
    l = with_group(l.withColumn("pair", F.concat("l_returnflag", "l_linestatus")), "pair")
    return points_from(normalise(l, ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]), "id", ["l_quantity", "l_extendedprice", "l_discount", "l_tax"], "grp")


def customer_groups(groups: int) -> Column:
    rich, nation = (F.col("c_acctbal") >= 5000).cast("int"), F.col("c_nationkey") % 6
    return {2: rich, 6: nation, 12: rich * 6 + nation}[groups]


def _customer_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    l = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_quantity", "l_linestatus")
    o = load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("c_custkey"))
    p = load(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), F.regexp_extract("p_brand", r"(\d+)", 1).cast("int").alias("brand"))
    return l.join(o, "l_orderkey").join(p, "l_partkey")


def brand_positions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per customer with orders: the positions p1..p10 of ten brands by quantity bought, ties to the smaller brand."""
    bought = _customer_lines(spark, sf_dir).groupBy("c_custkey").agg(*[F.sum(F.when(F.col("brand") == b, F.col("l_quantity")).otherwise(0.0)).alias(f"q{b}") for b in range(1, RANKED_BRANDS + 1)])
    ahead = lambda b: sum(((F.col(f"q{o}") > F.col(f"q{b}")) | ((F.col(f"q{o}") == F.col(f"q{b}")) & F.lit(o < b))).cast("int") for o in range(1, RANKED_BRANDS + 1) if o != b)
    return bought.select("c_custkey", *[ahead(b).alias(f"p{b}") for b in range(1, RANKED_BRANDS + 1)])


def rank10(spark: SparkSession, sf_dir: str, groups: int = 2) -> DataFrame:
    """Stand-in for the ranking set: pair-sign encoded rankings, whose l1 distance is the number of inverted pairs."""
    return of_groups(rank10_by_all(spark, sf_dir, (groups,)), groups)


def rank10_by_all(spark: SparkSession, sf_dir: str, groups: Sequence[int] = (2, 6, 12)) -> DataFrame:
    r = brand_positions(spark, sf_dir).join(load(spark, sf_dir, "customer").select("c_custkey", "c_acctbal", "c_nationkey"), "c_custkey")
    return points_by_all(r, "c_custkey", encode_ranking([F.col(f"p{b}") for b in range(1, RANKED_BRANDS + 1)]), {g: customer_groups(g) for g in groups})


def score50(spark: SparkSession, sf_dir: str, groups: int = 2) -> DataFrame:
    """Stand-in for the score set: 25 brands x 2 line states, scores 0..4 by average quantity."""
    return of_groups(score50_by_all(spark, sf_dir, (groups,)), groups)


def score50_by_all(spark: SparkSession, sf_dir: str, groups: Sequence[int] = (2, 6, 12)) -> DataFrame:
    """Averages by customer and cell first: a row with all 50 as sums and counts would cross the exchange for nearly every line item."""
    cell = F.when(F.col("brand").between(1, 25) & F.col("l_linestatus").isin("F", "O"), F.col("brand") * 2 - F.when(F.col("l_linestatus") == "F", 2).otherwise(1))
    lines = _customer_lines(spark, sf_dir).select("c_custkey", cell.alias("cell"), "l_quantity").repartition("c_custkey")  # serves both groupings
    score = F.least(F.lit(4), F.floor(F.col("mean") / 10)).cast("double")
    filled = F.when(F.col("cell").isNotNull() & F.col("mean").isNotNull(), F.struct("cell", score.alias("score")))
    rows = lines.groupBy("c_custkey", "cell").agg(F.avg("l_quantity").alias("mean")).groupBy("c_custkey").agg(F.map_from_entries(F.collect_list(filled)).alias("scores"))
    rows = rows.join(load(spark, sf_dir, "customer").select("c_custkey", "c_acctbal", "c_nationkey"), "c_custkey")
    vec = F.transform(F.sequence(F.lit(0), F.lit(49)), lambda i: F.coalesce(F.try_element_at("scores", i), F.lit(0.0)))
    return points_by_all(rows, "c_custkey", vec, {g: customer_groups(g) for g in groups})


def dochash(spark: SparkSession, sf_dir: str, dim: int = 256, groups: int = 2, packed: bool = False) -> DataFrame:
    """Stand-in for the image set: signed hashed token counts of labelled documents (256 to 15,360 dimensions); groups by quality, or quality x toxic."""
    labels = load(spark, sf_dir, "labels").where("quality is not null and toxic is not null")
    docs = load(spark, sf_dir, "documents").select("doc_id", "text").join(labels, "doc_id")
    grp = F.col("quality") if groups == 2 else F.col("quality") * 2 + F.col("toxic")
    return hashed_points(docs.withColumn("grp", grp), "doc_id", "grp", "text", dim, packed=packed)


def doclang(spark: SparkSession, sf_dir: str, dim: int = 256, hash: str = "xxhash64") -> DataFrame:
    d = with_group(load(spark, sf_dir, "documents").select("doc_id", "text", "lang"), "lang")
    return hashed_points(d, "doc_id", "grp", "text", dim, hash)


#: Token hashes: the fast one, and one that other engines have too.
TOKEN_HASH = {"xxhash64": lambda t: F.xxhash64(t), "md5": lambda t: F.conv(F.substring(F.md5(t.cast("binary")), 1, 15), 16, 10).cast("long")}


def hashed_points(df: DataFrame, point_id: str, group: str, text: str, dim: int, hash: str = "xxhash64", packed: bool = False) -> DataFrame:
    """Signed token counts by an Arrow kernel (wide vectors would make expressions quadratic); ``packed``: as ``frames.packed`` gives them, without dense rows."""
    ship_package(df.sparkSession)
    rows = df.select(F.col(point_id).cast("long").alias("point_id"), F.col(group).cast("int").alias("grp"), F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+"), lambda t: t != "").alias("t"))
    rows = rows.select("point_id", "grp", F.transform("t", TOKEN_HASH[hash]).alias("h"))

    def run(batches):
        for batch in batches:
            for i in range(0, batch.num_rows, 256):
                b = batch.slice(i, 256)
                lens = b.column(2).value_lengths().to_numpy(zero_copy_only=False)
                h = b.column(2).flatten().to_numpy(zero_copy_only=False).astype(np.int64)
                row = np.repeat(np.arange(len(lens)), lens)
                sign = np.where((h >> 40) & 1, -1.0, 1.0)
                if packed:
                    yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(packed_sums(row, np.mod(h, dim), sign, len(lens), dim), pa.binary())], names=["point_id", "grp", "vec"])
                    continue
                out = np.bincount(row * dim + np.mod(h, dim), sign, len(lens) * dim)
                vec = pa.ListArray.from_arrays(pa.array(np.arange(0, out.size + 1, dim), pa.int32()), pa.array(out))
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), vec], names=["point_id", "grp", "vec"])

    return rows.mapInArrow(run, POINT.replace("array<double>", "binary") if packed else POINT)


def emb64(spark: SparkSession, sf_dir: str, groups: int = 4) -> DataFrame:
    e = load(spark, sf_dir, "embeddings")
    return e.select(F.col("vec_id").alias("point_id"), (F.col("label") % groups).cast("int").alias("grp"), F.col("embedding").cast("array<double>").alias("vec"))


def uniform_columns(rows: DataFrame, dim: int, m: int, scale: float, seed: int) -> DataFrame:
    """Points of ids ``(id)``: every coordinate is a hash of (id, dimension)."""
    unit = lambda j: F.shiftrightunsigned(F.xxhash64("id", j, F.lit(seed)), 11) * F.lit(scale / 2**53)
    return rows.select(F.col("id").alias("point_id"), F.pmod(F.xxhash64("id", F.lit(seed + 1)), F.lit(m)).cast("int").alias("grp"), F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), unit).alias("vec"))


def uniform_points(spark: SparkSession, n: int, dim: int = 1000, m: int = 4, scale: float = 1e5, seed: int = 7) -> DataFrame:
    """The uniform set at any size; any partitioning gives the same points."""
    return uniform_columns(spark.range(n), dim, m, scale, seed)


def event_points(events: DataFrame, types: Sequence[str]) -> DataFrame:
    """Stream or batch events as points: value, hour, weekday, log value; one group per event type (fixed list, so it works on streams)."""
    grp = F.array_position(F.array(*[F.lit(t) for t in types]), F.col("event_type")) - 1
    e = events.where(grp >= 0)
    return points_from(e, "event_id", [F.col("value") / 100, F.hour("ts") / F.lit(24.0), F.dayofweek("ts") / F.lit(7.0), F.round(F.log1p("value"), 6)], grp)


def evt4(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "events")
    types = sorted(r[0] for r in e.select("event_type").distinct().collect())
    return event_points(e, types)


def user_rankings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users' rankings of five event types by count (many equal rows), grouped by the market segment of the joined customer."""
    e = load(spark, sf_dir, "events").select("user_id", "event_type")
    types = sorted(r[0] for r in e.select("event_type").distinct().collect())
    n = e.groupBy("user_id").agg(*[F.sum((F.col("event_type") == t).cast("int")).alias(f"n{i}") for i, t in enumerate(types)])
    k = range(len(types))
    ahead = lambda b: sum(((F.col(f"n{o}") > F.col(f"n{b}")) | ((F.col(f"n{o}") == F.col(f"n{b}")) & F.lit(o < b))).cast("int") for o in k if o != b)
    c = with_group(load(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment"), "c_mktsegment")
    return n.join(c, n.user_id == c.c_custkey).select(F.col("user_id").alias("point_id"), F.col("grp").cast("int"), encode_ranking([ahead(b) for b in k]).alias("vec"))


def page_points(spark: SparkSession, sf_dir: str, dim: int = 64, top: int = 5, hash: str = "xxhash64") -> DataFrame:
    """Pages by hashed tokens of their HTML; groups are the most frequent hosts and the rest."""
    p = load(spark, sf_dir, "pages").select("page_id", "html", F.coalesce(F.try_parse_url("url", F.lit("HOST")), F.lit("")).alias("host"))
    hosts = p.groupBy("host").count().orderBy(F.col("count").desc(), "host").limit(top).withColumn("grp", F.row_number().over(W.orderBy(F.col("count").desc(), "host")) - 1)
    p = p.join(F.broadcast(hosts.select("host", "grp")), "host", "left").withColumn("grp", F.coalesce("grp", F.lit(top)))
    return hashed_points(p, "page_id", "grp", "html", dim, hash)


def conversation_points(spark: SparkSession, sf_dir: str, dim: int = 64, hash: str = "xxhash64") -> DataFrame:
    c = with_group(load(spark, sf_dir, "conversations").withColumn("id", F.col("conv_id") * 100000 + F.col("turn")), "role")
    return hashed_points(c, "id", "grp", "text", dim, hash)


def benchmark_points(spark: SparkSession, sf_dir: str, dim: int = 64, hash: str = "xxhash64") -> DataFrame:
    return hashed_points(load(spark, sf_dir, "benchmark").withColumn("grp", F.lit(0)), "item_id", "grp", "text", dim, hash)


def nation_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One point per nation (25 at every scale): mean balance of customers and suppliers, number of customers in thousands of the mean; groups are regions."""
    c = load(spark, sf_dir, "customer").groupBy("c_nationkey").agg(F.avg("c_acctbal").alias("a"), F.count("*").alias("n"))
    s = load(spark, sf_dir, "supplier").groupBy("s_nationkey").agg(F.avg("s_acctbal").alias("b"))
    n = load(spark, sf_dir, "nation")
    n = n.join(c, n.n_nationkey == c.c_nationkey, "left").join(s, n.n_nationkey == s.s_nationkey, "left")
    feats = [F.round(F.coalesce(F.col("a"), F.lit(0.0)) / 1000, 6), F.round(F.coalesce(F.col("b"), F.lit(0.0)) / 1000, 6), F.coalesce(F.col("n"), F.lit(0)).cast("double") / 10]
    return points_from(n, "n_nationkey", feats, "n_regionkey")


WORKLOADS = {
    "rankings": rank10,
    "scores": score50,
    "census": line6,
    "documents": lambda spark, d, groups=2: dochash(spark, d, 256, groups),
    "uniform": lambda spark, d, groups=4: emb64(spark, d, groups),
}
#: Sets whose group counts are columns of one build.
WORKLOADS_BY_ALL = {"rankings": rank10_by_all, "scores": score50_by_all, "census": line6_by_all}
#: Group counts of each workload's rows in the reports (fixed values).
WORKLOAD_GROUPS = {"rankings": (2, 6, 12), "scores": (2, 6, 12), "census": (2, 5, 10), "documents": (2, 4), "uniform": (4,)}
