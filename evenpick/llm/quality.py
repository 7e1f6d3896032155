"""Quality classifier: a generalised additive model with pairwise interactions.

Cyclic boosting of shallow trees, one feature (then one pair) after the other, leaves a lookup table for each feature and pair; a
document's score is the sum of its bins' entries. Features are counts over the whole text.

Defined results: null and empty texts have the feature values of the empty text and get a score like any other; without any usable
label the score is 0.5 for all; repeated rows repeat; an empty table gives no rows; other columns are carried along.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from evenpick.llm.labelled import TRAIN_ROWS, held_out, training_documents
from evenpick.llm.textbits import U, bounded_slices, lowered, mapped, prefix_hash, span_hash, utf8_buffer, without, words
from evenpick.plans.durable import ship_package

FEATURES = (
    "log_words", "word_length", "upper_share", "symbol_share", "bar_rate", "exclaim_rate", "digit_share", "distinct_share",
    "echo_share", "line_repeat_share", "line_words", "stop_rate", "comma_rate", "wide_share", "longest_word", "short_share", "upper_word_share",
)


def _flags(members: bytes) -> np.ndarray:
    out = np.zeros(256, bool)
    out[list(members)] = True
    return out


_UPPER, _LOWER = _flags(bytes(range(65, 91))), _flags(bytes(range(97, 123)))
_SYMBOL, _DIGIT, _WIDE = _flags(b"#$%&*@^~<>{}[]\\/_=+"), _flags(b"0123456789"), _flags(bytes(range(128, 256)))


def _per_doc(flag: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    total = np.zeros(len(flag) + 1, np.int64)
    np.cumsum(flag, out=total[1:])
    return np.diff(total[bounds]).astype(float)


def _distinct(doc: np.ndarray, hashes: np.ndarray, n: int) -> np.ndarray:
    """Number of distinct hashes of each document: one sort of (document, 44 bits of hash)."""
    keys = np.sort((doc.astype(U) << U(44)) | (hashes >> U(20)))
    fresh = np.ones(len(keys), bool)
    fresh[1:] = keys[1:] != keys[:-1]
    return np.bincount((keys[fresh] >> U(44)).astype(np.int64), minlength=n).astype(float)


def text_features(array: pa.Array) -> np.ndarray:
    """One row of ``FEATURES`` per text."""
    buf, off = utf8_buffer(array)
    n = len(off) - 1
    start, end, first = words(buf, off)
    n_words = np.diff(first).astype(float)
    doc = np.repeat(np.arange(n), np.diff(first))
    w, size = np.maximum(n_words, 1), np.maximum(np.diff(off), 1).astype(float)
    length = (end - start).astype(float)
    upper, lower = _per_doc(_UPPER[buf], off), _per_doc(_LOWER[buf], off)
    prefix = prefix_hash(lowered(buf))
    hashes = span_hash(prefix, start, end)
    echo = np.zeros(len(start), bool)
    echo[1:] = (hashes[1:] == hashes[:-1]) & (doc[1:] == doc[:-1])
    longest = np.zeros(n)
    np.maximum.at(longest, doc, length)
    newline = buf == 10
    inner = np.unique(np.concatenate([off[:-1], np.flatnonzero(newline) + 1]))
    inner = inner[inner < len(buf)]
    line_end = np.append(inner[1:], len(buf))
    line_doc = np.searchsorted(off, inner, "right") - 1
    lines = np.bincount(line_doc, minlength=n).astype(float)
    line_hash = span_hash(prefix, inner, np.maximum(inner, line_end - newline[line_end - 1])) if len(inner) else np.zeros(0, U)
    last = buf[end - 1] if len(end) else np.zeros(0, np.uint8)
    up = _per_doc(_UPPER[buf[start]] & _UPPER[last], first) if len(start) else np.zeros(n)
    columns = (
        np.log1p(n_words), _per_doc_sum(length, first) / w, upper / np.maximum(upper + lower, 1), _per_doc(_SYMBOL[buf], off) / size,
        _per_doc(buf == 124, off) / w, _per_doc(buf == 33, off) / w, _per_doc(_DIGIT[buf], off) / size, _distinct(doc, hashes, n) / w,
        _per_doc(echo, first) / w, 1 - _distinct(line_doc, line_hash, n) / np.maximum(lines, 1), n_words / np.maximum(lines, 1),
        _per_doc(last == 46, first) / w, _per_doc(buf == 44, off) / w, _per_doc(_WIDE[buf], off) / size, np.log1p(longest),
        _per_doc(length <= 3, first) / w, up / w,
    )
    return np.stack(columns, 1)


def _per_doc_sum(values: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    total = np.zeros(len(values) + 1)
    np.cumsum(values, out=total[1:])
    return np.diff(total[bounds])


@dataclass
class AdditiveModel:
    """Bin edges and tables: ``intercept + sum of single[f][bin] + sum of pairs[(f, g)][coarse bin, coarse bin]``."""

    edges: list[np.ndarray]
    coarse: list[np.ndarray]
    intercept: float = 0.0
    single: list[np.ndarray] = field(default_factory=list)
    pairs: dict[tuple[int, int], np.ndarray] = field(default_factory=dict)

    def margin(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.intercept)
        fine = [np.searchsorted(e, x[:, f], "right") for f, e in enumerate(self.edges)]
        for table, b in zip(self.single, fine):
            out += table[b]
        for (f, g), table in self.pairs.items():
            out += table[np.searchsorted(self.coarse[f], x[:, f], "right"), np.searchsorted(self.coarse[g], x[:, g], "right")]
        return out

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.margin(x), -30, 30)))


def _edges(x: np.ndarray, bins: int) -> np.ndarray:
    return np.unique(np.quantile(x, np.linspace(0, 1, bins + 1)[1:-1]))


def _gain(g, h, ridge):
    return g * g / (h + ridge)


def _stump_table(g: np.ndarray, h: np.ndarray, leaves: int, ridge: float) -> np.ndarray:
    """A tree with few leaves over ordered bins, as the table of its leaf values."""
    cg, ch = np.concatenate([[0], np.cumsum(g)]), np.concatenate([[0], np.cumsum(h)])
    parts = [(0, len(g))]
    while len(parts) < leaves:
        best, where = 1e-9, None
        for i, (a, b) in enumerate(parts):
            if b - a < 2:
                continue
            m = np.arange(a + 1, b)
            gain = _gain(cg[m] - cg[a], ch[m] - ch[a], ridge) + _gain(cg[b] - cg[m], ch[b] - ch[m], ridge) - _gain(cg[b] - cg[a], ch[b] - ch[a], ridge)
            if gain.max() > best:
                best, where = gain.max(), (i, int(m[gain.argmax()]))
        if where is None:
            break
        i, m = where
        a, b = parts.pop(i)
        parts += [(a, m), (m, b)]
    out = np.zeros(len(g))
    for a, b in parts:
        out[a:b] = (cg[b] - cg[a]) / (ch[b] - ch[a] + ridge)
    return out


def _cross_table(g: np.ndarray, h: np.ndarray, ridge: float) -> tuple[np.ndarray, float]:
    """The best one cut on each axis: a table of four leaves and its gain."""
    cg, ch = g.cumsum(0).cumsum(1), h.cumsum(0).cumsum(1)
    if min(g.shape) < 2:
        return np.zeros_like(g), 0.0
    a, b = cg[:-1, :-1], ch[:-1, :-1]
    quads = [
        (a, b), (cg[:-1, -1:] - a, ch[:-1, -1:] - b), (cg[-1:, :-1] - a, ch[-1:, :-1] - b),
        (cg[-1, -1] - cg[:-1, -1:] - cg[-1:, :-1] + a, ch[-1, -1] - ch[:-1, -1:] - ch[-1:, :-1] + b),
    ]
    gain = sum(_gain(x, y, ridge) for x, y in quads)
    i, j = np.unravel_index(gain.argmax(), gain.shape)
    value = [x[i, j] / (y[i, j] + ridge) for x, y in quads]
    out = np.empty_like(g)
    out[: i + 1, : j + 1], out[: i + 1, j + 1 :], out[i + 1 :, : j + 1], out[i + 1 :, j + 1 :] = value
    return out, float(gain[i, j] - _gain(cg[-1, -1], ch[-1, -1], ridge))


def fit_additive(x: np.ndarray, y: np.ndarray, bins=64, coarse_bins=12, cycles=120, pair_cycles=40, pairs=6, rate=0.15, leaves=3, ridge=2.0) -> AdditiveModel:
    """Fit on a bounded sample: singles in cycles, then the strongest pairs on what singles leave."""
    n_features = x.shape[1]
    if not len(y) or y.min() == y.max():
        share = (y.sum() + 0.5) / (len(y) + 1)
        empty = [np.zeros(0) for _ in range(n_features)]
        return AdditiveModel(empty, empty, float(np.log(share / (1 - share))), [np.zeros(1) for _ in range(n_features)])
    model = AdditiveModel([_edges(x[:, f], bins) for f in range(n_features)], [_edges(x[:, f], coarse_bins) for f in range(n_features)])
    model.intercept = float(np.log(y.mean() / (1 - y.mean())))
    fine = [np.searchsorted(e, x[:, f], "right") for f, e in enumerate(model.edges)]
    model.single = [np.zeros(len(e) + 1) for e in model.edges]
    margin = np.full(len(y), model.intercept)

    def slope():
        p = 1 / (1 + np.exp(-np.clip(margin, -30, 30)))
        return y - p, p * (1 - p)

    for _ in range(cycles):
        for f, b in enumerate(fine):
            g, h = slope()
            k = len(model.single[f])
            step = rate * _stump_table(np.bincount(b, g, k), np.bincount(b, h, k), leaves, ridge)
            model.single[f] += step
            margin += step[b]
    rough = [np.searchsorted(e, x[:, f], "right") for f, e in enumerate(model.coarse)]
    shape = [len(e) + 1 for e in model.coarse]

    def sums(f, k, g, h):
        cell, cells = rough[f] * shape[k] + rough[k], shape[f] * shape[k]
        return np.bincount(cell, g, cells).reshape(shape[f], -1), np.bincount(cell, h, cells).reshape(shape[f], -1)

    g, h = slope()
    ranked = sorted(combinations(range(n_features), 2), key=lambda p: -_cross_table(*sums(*p, g, h), ridge)[1])[:pairs]
    model.pairs = {p: np.zeros((shape[p[0]], shape[p[1]])) for p in ranked}
    for _ in range(pair_cycles):
        for f, k in ranked:
            step = rate * _cross_table(*sums(f, k, *slope()), ridge)[0]
            model.pairs[f, k] += step
            margin += step[rough[f], rough[k]]
    return model


def feature_table(docs: DataFrame, keep: tuple[str, ...]) -> DataFrame:
    """``keep`` columns and the feature vector of each document."""
    ship_package(docs.sparkSession)
    chosen = docs.select(*keep, "text")

    def run(batches):
        for b in bounded_slices(batches):
            x = text_features(b.column(len(keep)))
            flat = pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, x.shape[1]), pa.int32()), pa.array(x.ravel()))
            yield pa.RecordBatch.from_arrays([*b.columns[: len(keep)], flat], names=[*keep, "features"])

    return chosen.mapInArrow(run, T.StructType([*chosen.schema.fields[: len(keep)], T.StructField("features", T.ArrayType(T.DoubleType()))]))


def train_quality(docs: DataFrame, labels: DataFrame, rows: int = TRAIN_ROWS) -> AdditiveModel:
    """Fit on at most ``rows`` labelled documents outside the held-out fold; only their feature rows reach the driver."""
    sample = feature_table(training_documents(docs, labels, "quality", rows), ("doc_id", "label")).orderBy("doc_id").limit(rows).toPandas()
    x = np.array(sample.features.tolist(), float).reshape(-1, len(FEATURES))
    return fit_additive(x, sample.label.to_numpy(float) if len(sample) else np.zeros(0))


def score_quality(docs: DataFrame, model: AdditiveModel, into: str = "quality_score") -> DataFrame:
    """``docs`` with one more column ``into``: how likely its quality label is 1."""
    ship_package(docs.sparkSession)
    kept = without(docs, into)
    at = kept.columns.index("text")

    def run(batches):
        for b in bounded_slices(batches, f"c{at}"):
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(model.score(text_features(b.column(at))))], names=[*b.schema.names, f"c{b.num_columns}"])

    return mapped(kept, run, [*kept.schema.fields, T.StructField(into, T.DoubleType())])


def score_ids(docs: DataFrame, model: AdditiveModel, threshold: float) -> DataFrame:
    """Per document: fold, score and decision; texts stay in the worker."""
    ship_package(docs.sparkSession)

    def run(batches):
        for b in bounded_slices(batches):
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(model.score(text_features(b.column(1))))], names=["doc_id", "score"])

    scored = docs.select("doc_id", "text").mapInArrow(run, "doc_id long, score double")
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
