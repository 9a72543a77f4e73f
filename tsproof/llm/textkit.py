"""Vectorised word handling for Arrow string columns (used inside ``mapInArrow`` functions).

Words are maximal runs of bytes outside ``{0x20, 0x09..0x0D}`` of the UTF-8 text.  All functions work on whole
batches with numpy, so no Python code runs per word.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U64 = np.uint64
_MASK = (1 << 64) - 1


def mix(x: np.ndarray) -> np.ndarray:
    """64-bit finaliser: every input bit reaches every output bit."""
    x = x.astype(U64, copy=True)
    x ^= x >> U64(30)
    x *= U64(0xBF58476D1CE4E5B9)
    x ^= x >> U64(27)
    x *= U64(0x94D049BB133111EB)
    x ^= x >> U64(31)
    return x


def stream_of(seed: int, n: int) -> np.ndarray:
    """n pseudo-random 64-bit values, the same on every machine."""
    with np.errstate(over="ignore"):
        return mix((np.arange(1, n + 1, dtype=U64) + U64(seed)) * U64(0x9E3779B97F4A7C15))


_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
#: Lower case, and ASCII punctuation as blanks.
PLAIN = _LOWER.copy()
PLAIN[[b for b in range(0x21, 0x7F) if not chr(b).isalnum()]] = 0x20
_BYTE = stream_of(7, 256)
_R = 0x9E6C63D0876A9A47  # odd, hence invertible modulo 2**64


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(max(n, 1), base & _MASK, dtype=U64)
    out[0] = 1
    return np.multiply.accumulate(out)


class Powers:
    """Powers of an odd base and of its inverse, grown on demand."""

    def __init__(self, base: int):
        self.base, self.inverse = base, pow(base, -1, 1 << 64)
        self.up = self.down = np.ones(1, dtype=U64)

    def get(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if n > len(self.up):
            self.up, self.down = _powers(self.base, n), _powers(self.inverse, n)
        return self.up, self.down


_BYTES = Powers(_R)
_WINDOWS = (Powers(0xD6E8FEB86659FD93), Powers(0xA0761D6478BD642F))


def pieces(batch: pa.RecordBatch, column: str, limit: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """Slices of a batch whose texts hold about ``limit`` bytes (one row at least), so memory stays bounded."""
    n = batch.num_rows
    if not n:
        return
    sizes = np.diff(buffers(batch.column(batch.schema.get_field_index(column)))[1])
    group = (np.cumsum(sizes) - sizes) // limit
    cuts = np.flatnonzero(np.diff(group)) + 1
    for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), n], strict=True):
        yield batch.slice(a, b - a)


def buffers(arr: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets (from 0) of a string or binary array; nulls count as empty."""
    if arr.null_count:
        arr = arr.fill_null(b"" if pa.types.is_binary(arr.type) or pa.types.is_large_binary(arr.type) else "")
    wide = pa.types.is_large_string(arr.type) or pa.types.is_large_binary(arr.type)
    _, off, data = arr.buffers()
    if len(arr) == 0 or off is None:
        return np.zeros(0, np.uint8), np.zeros(len(arr) + 1, np.int64)
    offsets = np.frombuffer(off, np.int64 if wide else np.int32)[arr.offset : arr.offset + len(arr) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]] if data is not None else np.zeros(0, np.uint8)
    return raw, offsets - offsets[0]


class Words:
    """Word boundaries of a string array: ``start``/``end`` byte positions, ``first[i]:first[i+1]`` words of row i."""

    def __init__(self, arr: pa.Array, lower: bool = False, table: np.ndarray | None = None):
        self.data, self.offsets = buffers(arr)
        if lower or table is not None:
            self.data = (_LOWER if table is None else table)[self.data]
        n = len(self.data)
        solid = ~_SPACE[self.data]
        edge = np.zeros(n + 1, bool)
        edge[self.offsets] = True
        begin, finish = solid.copy(), solid.copy()
        if n:
            begin[1:] &= ~solid[:-1] | edge[1:n]
            finish[:-1] &= ~solid[1:] | edge[1:n]
        self.start = np.flatnonzero(begin)
        self.end = np.flatnonzero(finish) + 1
        self.first = np.searchsorted(self.start, self.offsets)

    def hashes(self) -> np.ndarray:
        """A 64-bit hash of each word."""
        n = len(self.data)
        up, down = _BYTES.get(n + 1)
        total = np.zeros(n + 1, dtype=U64)
        np.cumsum(_BYTE[self.data] * up[:n], out=total[1:])
        return mix((total[self.end] - total[self.start]) * down[self.start] + (self.end - self.start).astype(U64))

    def counts(self) -> np.ndarray:
        return np.diff(self.first)


def windows(words: np.ndarray, width: int, lane: int = 0) -> np.ndarray:
    """Hash of each run of ``width`` consecutive words (positions 0..n-width, across row borders)."""
    n = len(words)
    if n < width:
        return np.zeros(0, dtype=U64)
    up, down = _WINDOWS[lane].get(n + 1)
    total = np.zeros(n + 1, dtype=U64)
    np.cumsum((mix(words + U64(lane)) if lane else words) * up[:n], out=total[1:])
    return mix((total[width:] - total[: n - width + 1]) * down[: n - width + 1])


def spans(words: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Hash of each run ``words[start:end]``; equals ``windows`` for runs of one width."""
    n = len(words)
    up, down = _WINDOWS[0].get(n + 1)
    total = np.zeros(n + 1, dtype=U64)
    np.cumsum(words * up[:n], out=total[1:])
    return mix((total[end] - total[start]) * down[start])


def inside(first: np.ndarray, width: int) -> np.ndarray:
    """Positions at which a window of ``width`` words lies within one row; ``first`` as in ``Words``."""
    n = int(first[-1]) - width + 1
    if n <= 0:
        return np.zeros(0, np.int64)
    room = np.repeat(first[1:], np.diff(first))[:n]
    pos = np.arange(n)
    return pos[pos + width <= room]


def runs(mask: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Half-open runs of True."""
    edge = np.diff(np.concatenate(([0], mask.astype(np.int8), [0])))
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
