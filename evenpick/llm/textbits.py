"""Arrow and NumPy helpers on whole texts: bounded slices, UTF-8 buffers, words, mixed 64-bit hashes."""

from __future__ import annotations

import gc
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Bytes of text per slice; NumPy temporaries are some tens of times as large.
SLICE_BYTES = 500_000
U = np.uint64


#: What operators remember in this worker between tasks: owner -> how to forget it.
MEMORIES: dict[str, Callable[[], None]] = {}


def forget_others(owner: str | None = None) -> None:
    """Workers serve one operator after the other: free what the others remember."""
    for other in [o for o in MEMORIES if o != owner]:
        MEMORIES.pop(other)()
        gc.collect()


def bounded_slices(batches, column: str = "text", limit: int = SLICE_BYTES, owner: str | None = None) -> Iterator[pa.RecordBatch]:
    """Cut record batches into slices of about ``limit`` bytes of text; a longer single text is a slice of its own."""
    forget_others(owner)
    for batch in batches:
        if not batch.num_rows:
            continue
        sizes = pc.fill_null(pc.binary_length(batch.column(batch.schema.get_field_index(column))), 0).to_numpy(zero_copy_only=False)
        part = (np.cumsum(sizes, dtype=np.int64) - sizes) // limit
        cuts = np.flatnonzero(np.diff(part)) + 1
        for a, b in zip([0, *cuts], [*cuts, batch.num_rows]):
            yield batch.slice(int(a), int(b - a))
        del batch, sizes, part
        pa.default_memory_pool().release_unused()


def mapped(df, run: Callable, fields: list):
    """``df.mapInArrow(run)`` whatever the columns are called: ``run`` sees them as c0, c1, ...; ``fields`` are the result's."""
    from pyspark.sql import types as T

    safe = T.StructType([T.StructField(f"c{i}", f.dataType) for i, f in enumerate(fields)])
    return df.toDF(*[f"c{i}" for i in range(len(df.columns))]).mapInArrow(run, safe).toDF(*[f.name for f in fields])


def without(df, column: str | None):
    """``df`` less one column, by its plain name (dots and backquotes included)."""
    quoted = lambda c: "`" + c.replace("`", "``") + "`"
    return df.select(*[quoted(c) for c in df.columns if c != column])


def utf8_buffer(array: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string array; null is the empty text."""
    array = pc.fill_null(array.cast(pa.large_binary()), b"")
    if not len(array):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offs, data = array.buffers()
    offsets = np.frombuffer(offs, np.int64)[array.offset : array.offset + len(array) + 1]
    buf = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return buf[offsets[0] : offsets[-1]], offsets - offsets[0]


def mix64(x: np.ndarray) -> np.ndarray:
    """Finaliser with full avalanche on uint64 (public splitmix constants)."""
    x = x.astype(U, copy=True)
    x ^= x >> U(30)
    x *= U(0xBF58476D1CE4E5B9)
    x ^= x >> U(27)
    x *= U(0x94D049BB133111EB)
    x ^= x >> U(31)
    return x


_BASE, _INVERSE = 0x9E3779B97F4A7C15, pow(0x9E3779B97F4A7C15, -1, 1 << 64)
_POWERS = [np.ones(1, U), np.ones(1, U)]


def _powers(n: int, inverse: bool = False) -> np.ndarray:
    held = _POWERS[inverse]
    if len(held) < n:
        size = max(n, 2 * len(held))
        full = np.full(size, _INVERSE if inverse else _BASE, U)
        full[0] = 1
        held = _POWERS[inverse] = np.multiply.accumulate(full)
    return held[:n]


_SALT = mix64(np.arange(256, dtype=U) + U(0x51ED270B))


def prefix_hash(buf: np.ndarray) -> np.ndarray:
    """H with H[j] - H[i] the weighted sum of bytes i..j-1; see ``span_hash``."""
    out = np.zeros(len(buf) + 1, U)
    np.cumsum(_SALT[buf] * _powers(len(buf)), out=out[1:])
    return out


def span_hash(prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit content hashes of the byte spans [start, end)."""
    return mix64((prefix[end] - prefix[start]) * _powers(len(prefix), True)[start] + (end - start).astype(U))


_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def words(buf: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, first word index of each document + total): words are runs of non-white bytes within a document."""
    solid = ~_SPACE[buf]
    begin, stop = solid.copy(), solid.copy()
    begin[1:] &= ~solid[:-1]
    stop[:-1] &= ~solid[1:]
    inner = offsets[(offsets > 0) & (offsets < len(buf))]
    begin[inner] = solid[inner]
    stop[inner - 1] = solid[inner - 1]
    start, end = np.flatnonzero(begin), np.flatnonzero(stop) + 1
    return start, end, np.searchsorted(start, offsets)


def lowered(buf: np.ndarray) -> np.ndarray:
    """ASCII letters in lower case."""
    return _LOWER[buf]
