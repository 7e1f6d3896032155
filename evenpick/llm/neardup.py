"""Near-duplicate groups by HyperMinHash sketches, banding, estimation and exact confirmation.

A document's set holds its distinct 5-word shingles. A sketch keeps, for each of 128 buckets of the hash range, the leading-zero count and
10 mantissa bits of the bucket's least hash. Bands of sketch registers bring candidates together; the Jaccard estimate from the
sketches (corrected for chance collisions) drops most false ones; the full sets decide.

Output stays linear in a group of any size. Equal sets are one class from the start. Classes that share a band are tied to the least class they
meet and then along a spanning forest of the most similar estimates; that makes families, outside of which no link can lie. The sets of
a family are compared in blocks of bounded size, and a block gives a spanning forest of its links, not its pairs.

Defined results: null or empty texts have an empty set, link with nothing and stay; with fewer than five words the whole sequence is one shingle; a null
``doc_id`` has no component and is not kept; rows that share a ``doc_id`` are one document; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evenpick.llm.components import connected_components
from evenpick.llm.textbits import U, bounded_slices, lowered, mix64, prefix_hash, span_hash, utf8_buffer, words
from evenpick.plans.durable import maybe_broadcast, ship_package, staged

SHINGLE_WORDS, BUCKET_BITS, MANTISSA_BITS = 5, 7, 10
BUCKETS = 1 << BUCKET_BITS
#: Set sizes up to which 8 or 16 wide bands are used (more bands than set elements that may differ); 32 bands beyond.
WIDE_BANDS = ((22, 8), (45, 16))
FULL_BANDS = 32
#: How far an estimate may lie below the asked similarity: for sets up to 200 shingles, and for larger ones.
SMALL_SET, SLACK_SMALL, SLACK = 200, 0.25, 0.18
#: Most members, and shingles, of a block that is compared within itself or with another.
BLOCK, BLOCK_SHINGLES = 1500, 2_000_000
BROADCAST_IDS = 300_000
_STARTS = np.arange(BUCKETS, dtype=U) << U(64 - BUCKET_BITS)
_STEP = mix64(np.arange(1, SHINGLE_WORDS + 1, dtype=U)) | U(1)


def shingle_sets(array: pa.Array) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each text."""
    buf, off = utf8_buffer(array)
    low = lowered(buf)
    start, end, first = words(low, off)
    word = span_hash(prefix_hash(low), start, end)
    n = len(word)
    full = np.zeros(max(n - SHINGLE_WORDS + 1, 0), U)
    for j in range(SHINGLE_WORDS):
        full += word[j : j + len(full)] * _STEP[j]
    full = mix64(full)
    out = []
    for a, b in zip(first[:-1].tolist(), first[1:].tolist()):
        if b - a >= SHINGLE_WORDS:
            s = np.sort(full[a : b - SHINGLE_WORDS + 1])
            fresh = np.ones(len(s), bool)
            fresh[1:] = s[1:] != s[:-1]
            out.append(s[fresh])
        elif b > a:
            out.append(mix64(np.array([(word[a:b] * _STEP[: b - a]).sum() + U(b - a)], U)))
        else:
            out.append(np.zeros(0, U))
    return out


def hyper_sketch(s: np.ndarray) -> np.ndarray:
    """Registers of a sorted set: 0 for an empty bucket, else 1 + (leading zeros, mantissa) of its least hash."""
    out = np.zeros(BUCKETS, np.uint16)
    if not len(s):
        return out
    at = np.searchsorted(s, _STARTS)
    at[at == len(s)] = len(s) - 1
    least = s[at]
    held = (least >> U(64 - BUCKET_BITS)) == (_STARTS >> U(64 - BUCKET_BITS))
    rest = (least << U(BUCKET_BITS)) | U(1 << (BUCKET_BITS - 1))
    zeros = (63 - np.floor(np.log2(rest.astype(np.float64)))).clip(0, 62).astype(U)
    mantissa = (rest << zeros << U(1)) >> U(64 - MANTISSA_BITS)
    out[held] = ((zeros << U(MANTISSA_BITS)) + mantissa + U(1))[held].astype(np.uint16)
    return out


def estimate_jaccard(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Jaccard estimates of register rows; equal registers that chance alone would give are taken off."""
    used = ((a | b) != 0).sum(-1)
    same = ((a == b) & (a != 0)).sum(-1)
    chance = 0.16992 * used / (1 << MANTISSA_BITS)
    return np.clip((same - chance) / np.maximum(used - chance, 1), 0, 1)


def _schemes(n: np.ndarray, similarity: float) -> np.ndarray:
    """Which of the three band counts each set size takes part in: its own and those of sizes it could link with."""
    edges = np.array([x for x, _ in WIDE_BANDS])
    low, high = np.searchsorted(edges, np.ceil(n * similarity)), np.searchsorted(edges, np.floor(n / similarity))
    return np.stack([(low <= k) & (k <= high) for k in range(len(WIDE_BANDS) + 1)])


def band_keys(sketches: np.ndarray, n: np.ndarray, similarity: float) -> tuple[np.ndarray, np.ndarray]:
    """(row, key) of every band that holds at least one register."""
    quads = sketches.view(U).reshape(len(sketches), -1)
    rows, keys = [], []
    for k, mine in enumerate(_schemes(n, similarity)):
        bands = WIDE_BANDS[k][1] if k < len(WIDE_BANDS) else FULL_BANDS
        q = quads[mine].reshape(mine.sum(), bands, quads.shape[1] // bands)
        h = np.zeros(q.shape[:2], U)
        for j in range(q.shape[2]):
            h = mix64(h * U(3) + q[:, :, j])
        h = mix64(h + mix64(np.arange(bands, dtype=U) + U(1000 * (k + 1))))
        r, b = np.nonzero(q.any(2))
        rows.append(np.flatnonzero(mine)[r])
        keys.append(h[r, b])
    return np.concatenate(rows), np.concatenate(keys)


def _sketch_rows(batches):
    for b in bounded_slices(batches):
        sets = shingle_sets(b.column(1))
        yield pa.RecordBatch.from_arrays(
            [b.column(0), pa.array([len(s) for s in sets], pa.int64()), pa.array([hashlib.blake2b(s.tobytes(), digest_size=16).digest() for s in sets], pa.binary()), pa.array([hyper_sketch(s).tobytes() for s in sets], pa.binary())],
            names=["doc_id", "n_shingles", "print", "sketch"],
        )


def _matrix(column: pa.Array) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.uint16).reshape(len(column), BUCKETS)


def _band_rows(similarity: float):
    def run(batches):
        for batch in batches:
            for i in range(0, batch.num_rows, 4000):
                b = batch.slice(i, 4000)
                rows, keys = band_keys(_matrix(b.column(2)), b.column(1).to_numpy(zero_copy_only=False), similarity)
                yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), b.column(0).take(pa.array(rows))], names=["key", "cls"])

    return run


def _floor(n: np.ndarray, similarity: float) -> np.ndarray:
    """Estimates below this cannot come from a linked pair but with negligible chance (small sets have coarser estimates)."""
    return np.where(n <= SMALL_SET, similarity - SLACK_SMALL, similarity - SLACK)


def _estimated(similarity: float):
    def run(batches):
        for batch in batches:
            for i in range(0, batch.num_rows, 4000):
                b = batch.slice(i, 4000)
                keep = estimate_jaccard(_matrix(b.column(3)), _matrix(b.column(4))) >= _floor(b.column(2).to_numpy(zero_copy_only=False), similarity)
                yield pa.RecordBatch.from_arrays(b.filter(pa.array(keep)).columns[:2], names=["u", "v"])

    return run


def _set_rows(batches):
    for b in bounded_slices(batches):
        sets = shingle_sets(b.column(1))
        flat = np.concatenate([*sets, np.zeros(0, U)]).view(np.int64)
        bounds = np.cumsum([0, *map(len, sets)])
        yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(pa.array(bounds, pa.int32()), pa.array(flat))], names=["cls", "shingles"])


class Unions:
    """Disjoint sets of numbers."""

    def __init__(self):
        self.up: dict[int, int] = {}

    def find(self, x: int) -> int:
        while self.up.setdefault(x, x) != x:
            self.up[x] = self.up[self.up[x]]
            x = self.up[x]
        return x

    def join(self, a: int, b: int) -> bool:
        a, b = self.find(a), self.find(b)
        self.up[max(a, b)] = min(a, b)
        return a != b


def _family_links(percent: int):
    """Links of a family's block (or of two blocks) that join what was apart, decided on full sets."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["n_shingles", "cls"], kind="stable")
        m = np.frombuffer(b"".join(pdf.sketch), np.uint16).reshape(-1, BUCKETS)
        cls, n, block = pdf.cls.to_numpy(), pdf.n_shingles.to_numpy(), pdf.block.to_numpy()
        two = len(np.unique(block)) > 1
        sizes = np.array([len(x) for x in pdf.shingles])
        _, flat = np.unique(np.concatenate(pdf.shingles.to_list()), return_inverse=True)
        ends = np.cumsum(sizes)
        low, marked, unions, out = _floor(n, percent / 100), np.zeros(flat.max() + 1, bool), Unions(), []
        root = np.arange(len(m))
        for i in range(1, len(m)):
            j = np.arange(np.searchsorted(n, -(-n[i] * percent // 100)), i)
            j = j[(root[j] != root[i]) & ((block[j] != block[i]) | (not two))]
            if len(j):
                j = j[estimate_jaccard(m[j], m[i]) >= low[j]]
            if not len(j):
                continue
            mine = flat[ends[i] - sizes[i] : ends[i]]
            marked[mine] = True
            at = np.repeat(ends[j] - np.cumsum(sizes[j]), sizes[j]) + np.arange(sizes[j].sum())
            shared = np.add.reduceat(marked[flat[at]].astype(np.int64), np.cumsum(sizes[j]) - sizes[j])
            marked[mine] = False
            for k in j[100 * shared >= percent * (sizes[j] + sizes[i] - shared)].tolist():
                if unions.join(k, i):
                    out.append((cls[k], cls[i]))
            root = np.array([unions.find(x) for x in range(len(m))]) if out and out[-1][1] == cls[i] else root
        return pd.DataFrame(out, columns=["u", "v"], dtype=np.int64)

    return run


def _bucket_forest(similarity: float):
    """A spanning forest, most similar pairs first, of a band bucket's block (or two) across what is not tied yet."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        m = np.frombuffer(b"".join(pdf.sketch), np.uint16).reshape(-1, BUCKETS)
        comp, n, cls = (pdf[c].to_numpy() for c in ("component", "n_shingles", "cls"))
        low = _floor(n, similarity)
        us, vs, es = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0)]
        for i in range(len(m) - 1):
            j = np.arange(i + 1, len(m))
            j = j[(comp[j] != comp[i]) & (np.minimum(n[j], n[i]) >= similarity * np.maximum(n[j], n[i]) - 1e-9)]
            if len(j):
                e = estimate_jaccard(m[j], m[i])
                ok = e >= np.minimum(low[j], low[i])
                us.append(np.full(ok.sum(), i)), vs.append(j[ok]), es.append(e[ok])
        u, v, e = np.concatenate(us), np.concatenate(vs), np.concatenate(es)
        unions = Unions()
        keep = [k for k in np.argsort(-e, kind="stable").tolist() if unions.join(int(comp[u[k]]), int(comp[v[k]]))]
        return pd.DataFrame({"u": cls[u[keep]], "v": cls[v[keep]]})

    return run


def _in_blocks(rows: DataFrame, blocks: Column, spread: Column) -> DataFrame:
    """Deal a group's rows into ``blocks`` blocks and send each row to every pair of blocks (lo, hi) that it takes part in."""
    rows = rows.withColumn("blocks", blocks).withColumn("block", F.pmod(spread, F.col("blocks")))
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    return rows.withColumn("lo", F.least("block", "other")).withColumn("hi", F.greatest("block", "other"))


class NearDuplicates:
    """The stages of one run over a document table."""

    def __init__(self, docs: DataFrame, percent: int = 80):
        ship_package(docs.sparkSession)
        self.docs, self.percent, self.similarity = docs, percent, percent / 100
        rows = docs.select("doc_id", "text").mapInArrow(_sketch_rows, "doc_id long, n_shingles long, print binary, sketch binary")
        self.rows = staged(rows, "sketches")
        known = self.rows.where("n_shingles > 0 and doc_id is not null")
        self.classes = staged(known.groupBy("print", "n_shingles").agg(F.min("doc_id").alias("cls"), F.first("sketch").alias("sketch")).select("cls", "n_shingles", "sketch", "print"), "classes")
        bands = self.classes.select("cls", "n_shingles", "sketch").mapInArrow(_band_rows(self.similarity), "key long, cls long").distinct()
        shared = bands.groupBy("key").agg(F.min("cls").alias("least"), F.count("*").alias("n")).where("n > 1")
        self.buckets = staged(bands.join(shared, "key"), "buckets")

    def estimated(self, pairs: DataFrame) -> DataFrame:
        sketches = self.classes.select("cls", "n_shingles", "sketch")
        a = pairs.join(sketches.toDF("u", "n", "a"), "u").join(sketches.toDF("v", "m", "b"), "v")
        a = a.where("100 * least(n, m) >= {0} * greatest(n, m)".format(self.percent))
        return a.select("u", "v", F.least("n", "m").alias("n"), "a", "b").mapInArrow(_estimated(self.similarity), "u long, v long")

    def forest(self, pairs: DataFrame) -> DataFrame:
        """Pairs that tie together what shares a band, is similar by estimate, and is not yet tied by ``pairs``."""
        comp = connected_components(pairs)
        rows = self.buckets.select("key", "cls").join(comp.toDF("cls", "component"), "cls", "left").withColumn("component", F.coalesce("component", "cls"))
        mixed = rows.groupBy("key").agg(F.min("component").alias("a"), F.max("component").alias("b"), F.count("*").alias("n")).where("a <> b")
        rows = staged(rows.join(mixed.select("key", "n"), "key"), "untied")
        small = rows.where("n = 2").groupBy("key").agg(F.min("cls").alias("u"), F.max("cls").alias("v"))
        small = self.estimated(small.select("u", "v").distinct())
        big = _in_blocks(rows.where("n > 2"), F.ceil(F.col("n") / BLOCK), F.xxhash64("cls", "key"))
        big = big.select("key", "cls", "component", "lo", "hi").join(self.classes.select("cls", "n_shingles", "sketch"), "cls")
        return big.groupBy("key", "lo", "hi").applyInPandas(_bucket_forest(self.similarity), "u long, v long").union(small).distinct()

    def links(self) -> DataFrame:
        """Confirmed links between classes, enough of them to join every component."""
        star = self.buckets.where("cls <> least").groupBy("cls").agg(F.min("least").alias("least"))
        star = staged(self.estimated(star.select(F.col("least").alias("u"), F.col("cls").alias("v"))), "star-pairs")
        tied = staged(star.union(self.forest(star)), "tied-pairs")
        families = staged(connected_components(tied).toDF("cls", "family"), "families")
        texts = self.docs.select("doc_id", "text").join(maybe_broadcast(families.select(F.col("cls").alias("doc_id")), BROADCAST_IDS), "doc_id", "left_semi")
        members = families.join(self.classes.select("cls", "n_shingles", "sketch"), "cls")
        weight = members.groupBy("family").agg(F.count("*").alias("n"), F.sum("n_shingles").alias("total"))
        rows = members.join(weight, "family").withColumn("blocks", F.ceil(F.greatest(F.col("n") / BLOCK, F.col("total") / BLOCK_SHINGLES)))
        rows = rows.join(texts.mapInArrow(_set_rows, "cls long, shingles array<long>"), "cls")
        rows = _in_blocks(rows, F.col("blocks"), F.xxhash64("cls")).select("family", "lo", "hi", "block", "cls", F.size("shingles").cast("long").alias("n_shingles"), "sketch", "shingles")
        return staged(rows.groupBy("family", "lo", "hi").applyInPandas(_family_links(self.percent), "u long, v long"), "links")

    def result(self) -> DataFrame:
        """(doc_id, n_shingles, component_id, kept) of every document row."""
        comp = connected_components(self.links()).toDF("cls", "component")
        of_class = self.classes.select("print", "n_shingles", "cls").join(comp, "cls", "left").select("print", "n_shingles", F.coalesce("component", "cls").alias("component"))
        rows = self.rows.select("doc_id", "n_shingles", "print")
        out = rows.join(of_class, ["print", "n_shingles"], "left")
        component = F.when(F.col("n_shingles") == 0, F.col("doc_id")).when(F.col("doc_id").isNotNull(), F.coalesce("component", "doc_id"))
        return out.select("doc_id", "n_shingles", component.alias("component_id")).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(False)))


def near_duplicates(docs: DataFrame, percent: int = 80) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept): groups of documents whose shingle sets have a Jaccard similarity of ``percent``/100 or more."""
    return NearDuplicates(docs, percent).result()
