"""Vectorised byte kernels over Arrow string columns.

Every function works on the whole texts of a slice of rows, held as one byte buffer with
row offsets, and costs a fixed number of NumPy passes over the bytes.  Null texts count as
empty.  Slices hold about ``CHUNK`` bytes (a longer text makes a slice of its own), so a
worker's memory is bounded by the longest text, never by the Arrow batch.
"""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

CHUNK = 1 << 19
U = np.uint64

#: White space of the word pattern: space, and the controls 9 to 13.
BLANK = np.zeros(256, bool)
BLANK[[9, 10, 11, 12, 13, 32]] = True
#: A-Z to a-z, every other byte as it is.
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

_TABLES = np.random.default_rng(20240131).integers(1, 1 << 63, (2, 256), dtype=np.uint64) * U(2) + U(1)
_BASES = (0x9E3779B97F4A7C15, 0xD1342543DE82EF95)


def mix(x: np.ndarray) -> np.ndarray:
    """Bijective 64-bit finaliser."""
    x = x ^ (x >> U(30))
    x = x * U(0xBF58476D1CE4E5B9)
    x ^= x >> U(27)
    x *= U(0x94D049BB133111EB)
    x ^= x >> U(31)
    return x


_POWERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _powers(which: int, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of a base and of its inverse, ``size`` at least; the table grows and is shared."""
    if which not in _POWERS or len(_POWERS[which][0]) < size:
        bits = max(19, int(size - 1).bit_length())
        out = []
        for base in (_BASES[which], pow(_BASES[which], -1, 1 << 64)):
            p = np.ones(1 << bits, np.uint64)
            for b in range(bits):
                p[1 << b : 2 << b] = p[: 1 << b] * U(pow(base, 1 << b, 1 << 64))
            out.append(p)
        _POWERS[which] = (out[0], out[1])
    return _POWERS[which]


class RollingHash:
    """Hashes of any byte ranges of one buffer (modulo 2**64, random byte weights, finalised).

    Eight bytes a byte for the sums, and tables of powers as long as the longest buffer yet.
    """

    def __init__(self, data: np.ndarray, which: int = 0, lower: bool = False):
        power, self.inverse = _powers(which, len(data) + 1)
        table = _TABLES[which][LOWER] if lower else _TABLES[which]
        self.sums = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(table[data] * power[: len(data)], out=self.sums[1:])

    def spans(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix((self.sums[end] - self.sums[start]) * self.inverse[start] + (end - start).astype(np.uint64))

    def grams(self, size: int) -> np.ndarray:
        """The hash of every range of ``size`` bytes, by its start."""
        n = len(self.sums) - size
        if n <= 0:
            return np.zeros(0, np.uint64)
        return mix((self.sums[size:] - self.sums[:n]) * self.inverse[:n] + U(size))


def slices(batch: pa.RecordBatch, column: str = "text", limit: int = CHUNK) -> Iterator[pa.RecordBatch]:
    """The batch in runs of rows whose texts hold about ``limit`` bytes together."""
    if not batch.num_rows:
        return
    size = np.asarray(pc.fill_null(pc.binary_length(batch.column(column)), 0), np.int64)
    total = np.cumsum(size)
    start = 0
    while start < len(size):
        before = total[start - 1] if start else 0
        stop = max(start + 1, int(np.searchsorted(total, before + limit, "right")))
        yield batch.slice(start, stop - start)
        start = stop


def buffer(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All bytes, and the offsets of the rows in them."""
    if texts.null_count:
        texts = pc.fill_null(texts, b"" if pa.types.is_binary(texts.type) or pa.types.is_large_binary(texts.type) else "")
    wide = pa.types.is_large_string(texts.type) or pa.types.is_large_binary(texts.type)
    _, offsets, data = texts.buffers()
    if offsets is None or not len(texts):
        return np.zeros(0, np.uint8), np.zeros(len(texts) + 1, np.int64)
    off = np.frombuffer(offsets, np.int64 if wide else np.int32)[texts.offset : texts.offset + len(texts) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8)[off[0] : off[-1]] if data is not None else np.zeros(0, np.uint8)
    return raw, off - off[0]


class Words:
    """The words (runs of non-blank bytes) of the rows of a slice: bounds, rows, hashes."""

    def __init__(self, texts: pa.Array, lower: bool = False):
        self.data, self.offsets = buffer(texts)
        n = len(self.data)
        ink = ~BLANK[self.data]
        edge = np.zeros(n + 1, bool)
        edge[self.offsets] = True
        begins, ends = ink.copy(), ink.copy()
        if n:
            begins[1:] &= ~ink[:-1] | edge[1:n]
            ends[:-1] &= ~ink[1:] | edge[1:n]
        self.ink = ink
        self.start, self.end = np.flatnonzero(begins), np.flatnonzero(ends) + 1
        #: word k of row d: of[d] <= k < of[d + 1]
        self.of = np.searchsorted(self.start, self.offsets)
        self.count = np.diff(self.of)
        self.row = np.repeat(np.arange(len(self.count)), self.count)
        self._lower = lower

    def hashes(self) -> np.ndarray:
        return RollingHash(self.data, 0, self._lower).spans(self.start, self.end)

    def shingles(self, size: int) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of all runs of ``size`` words inside a row, and where each row's begin; a row
        with fewer words (one at least) has its whole sequence as the only one."""
        h = self.hashes()
        n = len(h) - size + 1
        total = np.zeros(max(n, 0), np.uint64)
        for j in range(size):
            total += h[j : j + n] * U(pow(_BASES[1], j + 1, 1 << 64)) if n > 0 else total
        total = mix(total + U(size))
        whole = np.flatnonzero((self.count > 0) & (self.count < size))
        inside = self.row[:n] == self.row[size - 1 :] if n > 0 else np.zeros(0, bool)
        per_row = np.maximum(self.count - size + 1, 0)
        if not len(whole):
            return total[inside], np.concatenate([[0], np.cumsum(per_row)])
        per_row[whole] = 1
        at = np.concatenate([[0], np.cumsum(per_row)])
        out = np.zeros(at[-1], np.uint64)
        short = np.zeros(len(out), bool)
        short[at[whole]] = True
        out[~short] = total[inside]
        for d in whole:
            own = h[self.of[d] : self.of[d + 1]]
            weights = np.array([pow(_BASES[1], j + 1, 1 << 64) for j in range(len(own))], np.uint64)
            out[at[d]] = mix(np.sum(own * weights, dtype=np.uint64, keepdims=True) + U(len(own)))[0]
        return out, at

    def per_row(self, flags: np.ndarray) -> np.ndarray:
        """Sums of a value per byte, by row."""
        sums = np.concatenate([[0], np.cumsum(flags, dtype=np.int64)])
        return np.diff(sums[self.offsets])


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)


def unsigned(x: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(x).view(np.uint64)


def sliding_argmin(values: np.ndarray, width: int) -> np.ndarray:
    """For each start, the place of the least of ``width`` values, the leftmost of equals; the
    values' upper 40 bits count.  Shorter than 2**24."""
    if len(values) < width:
        return np.zeros(0, np.int64)
    v = (values & ~U(0xFFFFFF)) | np.arange(len(values), dtype=np.uint64)
    span = 1
    while span * 2 <= width:
        v = np.minimum(v[: len(v) - span], v[span:])
        span *= 2
    if span < width:
        v = np.minimum(v[: len(v) - (width - span)], v[width - span :])
    return (v & U(0xFFFFFF)).astype(np.int64)


#: Type of what ``packed`` makes of a key and two columns.
PACKED = "kind int, block int, c0 binary, c1 binary, c2 binary"


def packed(kind: int, parts: int, key: np.ndarray, *columns: np.ndarray) -> pa.RecordBatch:
    """Rows in ascending order of ``key``, packed by range of the key: one row for each range that has some."""
    block = ((key >> U(32)) * U(parts)) >> U(32)
    edge = np.flatnonzero(np.concatenate([[True], block[1:] != block[:-1]]))
    ends = np.append(edge, len(key))
    arrays = [pa.array(np.full(len(edge), kind, np.int32)), pa.array(block[edge].astype(np.int32))]
    for c in (key, *columns):
        offsets = pa.array((ends * (c.itemsize * (c.shape[1] if c.ndim > 1 else 1))).astype(np.int32))
        arrays.append(pa.Array.from_buffers(pa.binary(), len(edge), [None, offsets.buffers()[1], pa.py_buffer(np.ascontiguousarray(c))]))
    return pa.RecordBatch.from_arrays(arrays, ["kind", "block", *(f"c{j}" for j in range(len(columns) + 1))])


class Memory(dict):
    """Results of a pure function by argument, in two generations of bounded size: what was not
    asked for during the last generation is forgotten (and computed again when asked for)."""

    def __init__(self, compute, size: int = 200_000, longest: int = 512):
        super().__init__()
        self.compute, self.size, self.longest, self.old = compute, size, longest, {}

    def forget(self) -> None:
        self.clear()
        self.old = {}

    def __missing__(self, key):
        value = self.old.get(key)
        if value is None:
            value = self.compute(key)
            if len(key) > self.longest:
                return value
        if len(self) >= self.size:
            self.old = dict(self)
            self.clear()
        self[key] = value
        return value


#: What modules keep in a worker between its tasks, and how to drop it.
KEPT: dict[str, Callable[[], None]] = {}


def tidy(fn: Callable) -> Callable:
    """``fn`` over record batches.  A worker that another operator used before drops that one's tables; at the end, as it
    may wait for long, it gives free memory back."""

    def run(batches):
        for module, drop in KEPT.items():
            if module != fn.__module__:
                drop()
        try:
            yield from fn(batches)
        finally:
            for which in [w for w, (power, _) in _POWERS.items() if len(power) > 2 * CHUNK]:
                del _POWERS[which]  # grown for a long text
            gc.collect()
            pa.default_memory_pool().release_unused()
            try:
                ctypes.CDLL(None).malloc_trim(0)
            except AttributeError:  # another C library
                pass

    return run
