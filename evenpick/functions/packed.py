"""Packed vectors: the nonzero components of wide and mostly zero rows, and l1 distances that read only those."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

#: Most vector components of a block of packed vectors that is made dense (16 MB of doubles).
BLOCK_VALUES = 2_000_000
#: Row sums up to this are exact in doubles, in any order, also as differences of two of them; the second: in single precision.
WHOLE, WHOLE_SINGLE = 2.0**50, 2.0**22


def pack(vec: np.ndarray) -> bytes:
    at = np.flatnonzero((vec != 0) | np.signbit(vec)).astype(np.int32)
    return np.int32(len(vec)).tobytes() + at.tobytes() + np.asarray(vec, float)[at].tobytes()


def unpack(raw: bytes) -> np.ndarray:
    out, n = np.zeros(np.frombuffer(raw, np.int32, 1)[0]), (len(raw) - 4) // 12
    out[np.frombuffer(raw, np.int32, n, 4)] = np.frombuffer(raw, float, n, 4 + 4 * n)
    return out


def packed_sums(row: np.ndarray, at: np.ndarray, values: np.ndarray, n: int, dim: int) -> list[bytes]:
    """The ``n`` packed vectors of the sums of ``values`` by row and component."""
    cell, entry = np.unique(row.astype(np.int64) * dim + at, return_inverse=True)
    sums = np.bincount(entry, values, len(cell))
    cell, sums = cell[sums != 0], sums[sums != 0]
    cuts, at, head = np.searchsorted(cell, np.arange(n + 1) * dim), (cell % dim).astype(np.int32), np.int32(dim).tobytes()
    return [head + at[a:b].tobytes() + sums[a:b].tobytes() for a, b in zip(cuts[:-1], cuts[1:])]


def whole_sum(values: np.ndarray, sums: np.ndarray) -> float:
    """The largest of ``sums`` (of absolute values) if all values are whole numbers, else infinity."""
    return float(sums.max(initial=0.0)) if np.isfinite(sums).all() and (values == np.rint(values)).all() else np.inf


class PackedRows:
    """Packed vectors under the indexing that kernels use: a row is dense, several rows stay packed.

    ``most`` bounds the rows' sums of absolute values where all values are whole numbers; elsewhere it is infinite.
    """

    def __init__(self, at: np.ndarray, values: np.ndarray, start: np.ndarray, dim: int, most: float | None = None):
        self.at, self.values, self.start, self.shape = at, values, start, (len(start) - 1, dim)
        self.most = whole_sum(values, self._sums(np.abs(values))) if most is None else most

    @classmethod
    def of(cls, column) -> PackedRows:
        """From a sequence of packed vectors of one length."""
        dims = {int.from_bytes(v[:4], "little") for v in column}
        if len(dims) > 1:
            raise ValueError("vectors must be of one length")
        sizes = np.array([(len(v) - 4) // 12 for v in column], np.int64)
        at = [np.frombuffer(v, np.int32, n, 4) for v, n in zip(column, sizes)]
        values = [np.frombuffer(v, float, n, 4 + 4 * n) for v, n in zip(column, sizes)]
        return cls(np.concatenate(at or [np.zeros(0, np.int32)]), np.concatenate(values or [np.zeros(0)]), np.concatenate([[0], np.cumsum(sizes)]), dims.pop() if dims else 0)

    @classmethod
    def of_dense(cls, x: np.ndarray) -> PackedRows:
        row, at = np.nonzero((x != 0) | np.signbit(x))
        return cls(at.astype(np.int32), x[row, at], np.searchsorted(row, np.arange(len(x) + 1)), x.shape[1])

    def _sums(self, entries: np.ndarray) -> np.ndarray:
        return np.bincount(np.repeat(np.arange(len(self)), np.diff(self.start)), entries, len(self))

    def __len__(self) -> int:
        return self.shape[0]

    def __getitem__(self, rows):
        if isinstance(rows, (int, np.integer)):
            i = range(len(self))[rows]
            out = np.zeros(self.shape[1])
            out[self.at[self.start[i] : self.start[i + 1]]] = self.values[self.start[i] : self.start[i + 1]]
            return out
        if isinstance(rows, slice) and rows.step in (None, 1):
            a, b, _ = rows.indices(len(self))
            start = self.start[a : max(a, b) + 1]
            return PackedRows(self.at[start[0] : start[-1]], self.values[start[0] : start[-1]], start - start[0], self.shape[1], self.most)
        rows = np.arange(len(self))[rows]
        sizes = np.diff(self.start)[rows]
        start = np.concatenate([[0], np.cumsum(sizes)])
        entry = np.repeat(self.start[rows] - start[:-1], sizes) + np.arange(start[-1])
        return PackedRows(self.at[entry], self.values[entry], start, self.shape[1], self.most)

    def dense(self) -> np.ndarray:
        out = np.zeros(self.shape)
        out[np.repeat(np.arange(len(self)), np.diff(self.start)), self.at] = self.values
        return out

    def parts(self, values: int) -> Iterator[slice]:
        """Slices of rows with at most ``values`` entries, a row at least."""
        a = 0
        while a < len(self):
            b = max(a + 1, int(np.searchsorted(self.start, self.start[a] + values, "right")) - 1)
            yield slice(a, b)
            a = b

    def dense_blocks(self, values: int = BLOCK_VALUES) -> Iterator[np.ndarray]:
        step = max(1, values // max(1, self.shape[1]))
        for i in range(0, len(self), step):
            yield self[i : i + step].dense()


def whole_l1(x: PackedRows, c: np.ndarray, cells: int = 262_144) -> np.ndarray | None:
    """l1 distances of packed rows to the dense rows ``c``, or None where a value is no whole number.

    A zero component adds ``|c|``, so a row starts from the center's norm and corrects it at its own entries. Sums of whole numbers are exact, so
    the distances are those of the dense rows.
    """
    norms = np.abs(c).sum(1)
    most = x.most + whole_sum(c, norms)
    if not most < WHOLE:
        return None
    kind = np.float32 if most < WHOLE_SINGLE else np.float64
    out, ct, values = np.empty((len(x), len(c))), np.ascontiguousarray(c.T, kind), x.values.astype(kind, copy=False)
    for rows in x.parts(max(1, cells // max(1, len(c)))):
        a, b = x.start[rows.start], x.start[rows.stop]
        got = ct[x.at[a:b]]
        size = np.abs(got)
        got -= values[a:b, None]
        np.abs(got, out=got)
        got -= size
        cuts = x.start[rows.start : rows.stop + 1] - a
        if len(c) > 8:
            for i in range(len(cuts) - 1):
                out[rows.start + i] = np.add.reduce(got[cuts[i] : cuts[i + 1]], axis=0)
            continue
        out[rows] = 0.0
        some = np.flatnonzero(np.diff(cuts))  # reduceat has no empty sums
        if len(some):
            out[rows.start + some] = np.add.reduceat(got, cuts[some], axis=0)
    out += norms
    return out
