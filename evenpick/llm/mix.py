"""Mixing sources to target weights by subset-sum budget fitting.

Documents are counted by exact length, a bounded knapsack over those counts fits what a source's whole
epochs leave of its budget, and the documents of each length are then picked in seeded hash order.

Defined results: a null or empty text has length 0 and is never repeated for its words; a null source is a
source of its own (last in order); an empty table gives an empty result; repeated rows count as rows (rows that
share id and length share their fate); columns of the input other than ``doc_id``, ``text`` and ``source`` are
carried along whatever their names.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from evenpick.plans.durable import maybe_broadcast, ship_package, staged

WORD = r"[^\x20\x09-\x0D]+"
#: Largest budget (in words) that the knapsack's bit set spans; larger remainders are first cut down by whole documents.
KNAPSACK_SPAN = 16_384
#: The cut table has one row per (source, length); up to this many rows it is broadcast, beyond it is joined by shuffle.
BROADCAST_ROWS = 200_000


def word_count(text: Column) -> Column:
    """Number of words of a text; null counts 0."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def fit_lengths(lengths, counts, budget: int, span: int = KNAPSACK_SPAN) -> dict[int, int]:
    """How many documents of each length to take so that their total is ``budget``, or as near below it as can be.

    Proportional shares first, then the longest documents until what is left fits ``span``, then an exact bounded
    subset-sum over the documents that are still free.
    """
    stock = {int(n): int(c) for n, c in zip(lengths, counts) if n > 0 and c > 0}
    whole = sum(n * c for n, c in stock.items())
    taken = dict.fromkeys(stock, 0)
    if budget >= whole:
        return stock
    left = budget
    if left > span:
        for n, c in stock.items():
            taken[n] = c * (budget - span) // whole
            left -= n * taken[n]
        for n in sorted(stock, reverse=True):
            if left <= span:
                break
            more = min(stock[n] - taken[n], left // n if n > span else -(-(left - span) // n))
            taken[n] += more
            left -= more * n
    left_most = min(left, span) if left <= span else left
    if left_most > span:  # only when every free document is longer than what is left
        return taken
    reach, mask, steps = 1, (1 << (left_most + 1)) - 1, []
    for n in sorted((n for n in stock if n <= left_most and stock[n] > taken[n]), key=lambda n: (-(stock[n] - taken[n]), n)):
        free, power = min(stock[n] - taken[n], left_most // n), 1
        while free > 0:
            k = min(power, free)
            before = reach
            reach |= (reach << (k * n)) & mask
            if reach != before:
                steps.append((n, k, before))
            free -= k
            power *= 2
        if reach >> left_most & 1:
            break
    at = reach.bit_length() - 1
    for n, k, before in reversed(steps):
        if not before >> at & 1:
            taken[n] += k
            at -= k * n
    return taken


def source_targets(sizes: DataFrame, weights: tuple[float, ...], ceiling: float) -> DataFrame:
    """(skey, source_size, target): shares of all words by weight, filled up to ``ceiling`` times a source's size.

    Rows are sources, so the two global windows see one row per source, never documents.
    """
    per = sizes.groupBy("skey").agg(F.first("source").alias("source"), F.sum("size").alias("source_size"))
    place = F.row_number().over(W.orderBy(F.col("source").asc_nulls_last(), "skey"))
    per = per.withColumn("weight", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), F.pmod(place - 1, F.lit(len(weights))) + 1))
    per = per.withColumn("cap", F.col("source_size") * F.lit(float(ceiling)))
    by_ratio = W.orderBy(F.col("cap") / F.col("weight"), "skey")
    before, onward = by_ratio.rowsBetween(W.unboundedPreceding, -1), by_ratio.rowsBetween(0, W.unboundedFollowing)
    total = F.sum("source_size").over(W.partitionBy())
    level = (total - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / F.sum("weight").over(onward)
    per = per.withColumn("level", level).withColumn("level", F.max("level").over(W.partitionBy()))
    return per.select("skey", "source_size", F.least("cap", F.col("level") * F.col("weight")).alias("target"))


def _fit_sources(batches):
    for pdf in batches:
        out = []
        for skey, size, target, lens in zip(pdf.skey, pdf.source_size, pdf.target, pdf.lens):
            budget = int(round(target))
            epochs = budget // size if size else 0
            extra = fit_lengths([r["size"] for r in lens], [r["n"] for r in lens], budget - epochs * size)
            out += [(skey, size, target, epochs, r["size"], extra.get(r["size"], 0)) for r in lens]
        yield pd.DataFrame(out, columns=["skey", "source_size", "target", "epochs", "size", "extra"])


def _keyed(docs: DataFrame, seed: int) -> DataFrame:
    return docs.select(
        "doc_id",
        "source",
        F.coalesce(F.concat(F.lit("="), F.col("source")), F.lit("")).alias("skey"),
        word_count(F.col("text")).alias("size"),
        F.xxhash64(F.col("doc_id"), F.lit(seed)).alias("pick"),
    )


def mix_plan(docs: DataFrame, weights=(5.0, 2.0, 1.0), ceiling: float = 3.0, seed: int = 17) -> tuple[DataFrame, DataFrame]:
    """The measured documents, and per (source, length) the epochs and the last hash of the extra picks.

    A pick is ``extra`` smallest hashes within (source, length). They are found in two levels: counts per slice of
    the hash range tell the slice that holds the last pick, and only that slice is ranked, so no window ever holds
    all documents of a hot (source, length).
    """
    ship_package(docs.sparkSession)
    sizes = staged(_keyed(docs, seed), "mix-sizes")
    lens = sizes.groupBy("skey", "size").agg(F.count("*").alias("n"))
    plan = source_targets(sizes, weights, ceiling).join(lens.groupBy("skey").agg(F.collect_list(F.struct("size", "n")).alias("lens")), "skey")
    plan = staged(plan.mapInPandas(_fit_sources, "skey string, source_size long, target double, epochs long, size long, extra long"), "mix-plan")
    slice_no = F.shiftright("pick", 56)
    partial = plan.where("extra > 0").select("skey", "size", "extra")
    sliced = sizes.join(maybe_broadcast(partial, BROADCAST_ROWS), ["skey", "size"]).withColumn("slice", slice_no)
    counts = sliced.groupBy("skey", "size", "slice").agg(F.count("*").alias("n"), F.first("extra").alias("extra"))
    run = F.sum("n").over(W.partitionBy("skey", "size").orderBy("slice"))
    last = counts.withColumn("upto", run).where("upto >= extra and upto - n < extra").select("skey", "size", "slice", (F.col("extra") - F.col("upto") + F.col("n")).alias("nth"))
    ranked = sliced.drop("extra").join(last, ["skey", "size", "slice"])
    ranked = ranked.withColumn("r", F.row_number().over(W.partitionBy("skey", "size", "slice").orderBy("pick")))
    cut = ranked.where("r = nth").select("skey", "size", F.col("pick").alias("cut"))
    return sizes, staged(plan.join(cut, ["skey", "size"], "left"), "mix-cuts")


def _copies() -> Column:
    return F.col("epochs") + F.coalesce((F.col("pick") <= F.col("cut")).cast("long"), F.lit(0))


def mix_report(docs: DataFrame, weights=(5.0, 2.0, 1.0), ceiling: float = 3.0, seed: int = 17) -> DataFrame:
    """One row per document: its size, its source's size and target, its copies and the words taken of it."""
    sizes, cuts = mix_plan(docs, weights, ceiling, seed)
    out = sizes.join(maybe_broadcast(cuts, BROADCAST_ROWS), ["skey", "size"]).withColumn("copies", _copies())
    return out.select("doc_id", "source", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"))


def mix_documents(docs: DataFrame, weights=(5.0, 2.0, 1.0), ceiling: float = 3.0, seed: int = 17) -> DataFrame:
    """The mix itself: every document row as often as the plan takes it; texts are not shuffled while the cut table fits a broadcast."""
    _, cuts = mix_plan(docs, weights, ceiling, seed)
    names = docs.columns
    row = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("__row"))
    keyed = row.select(
        "__row",
        F.coalesce(F.concat(F.lit("="), F.col("__row.source")), F.lit("")).alias("skey"),
        word_count(F.col("__row.text")).alias("size"),
        F.xxhash64(F.col("__row.doc_id"), F.lit(seed)).alias("pick"),
    )
    chosen = keyed.join(maybe_broadcast(cuts, BROADCAST_ROWS), ["skey", "size"]).withColumn("copies", _copies()).where("copies > 0")
    repeated = chosen.select("__row", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies"))).alias("__copy"))
    return repeated.select("__row.*")
