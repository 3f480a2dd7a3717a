"""Vectorised words and 64-bit hashes over Arrow text columns.

Everything here works on whole texts, on raw UTF-8, and in bounded memory: a batch is cut into slices of about ``SLICE`` bytes
(at least one document each), so a worker's arrays follow the slice, not the batch.
"""

from __future__ import annotations

import ctypes
import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

SLICE = 1_000_000
#: Words longer than this are hashed one by one, so that one long run does not make thousands of passes.
LONG_WORD = 512

_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_MASK = np.array([(1 << 8 * k) - 1 for k in range(8)] + [2**64 - 1], np.uint64)
_M1, _M2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)
_S = np.uint64(32)


try:
    _TRIM = ctypes.CDLL(None).malloc_trim
except (AttributeError, OSError):  # another C library
    _TRIM = None


def relax() -> None:
    """Gives freed memory back: idle workers stay alive between tasks, and what they hold is missing elsewhere."""
    pa.default_memory_pool().release_unused()
    if _TRIM is not None:
        _TRIM(0)


def mix(h: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values."""
    h = (h ^ (h >> _S)) * _M2
    h = (h ^ (h >> _S)) * _M2
    return h ^ (h >> _S)


@dataclass
class Slice:
    """Documents ``first … first+n-1`` of a batch; word ``i`` is ``data[start[i]:end[i]]``; document ``d`` owns words ``at[d]:at[d+1]``."""

    first: int
    n: int
    data: np.ndarray
    offsets: np.ndarray
    start: np.ndarray
    end: np.ndarray
    at: np.ndarray

    def hashes(self) -> np.ndarray:
        return hash_spans(self.data, self.start, self.end)

    def word(self, i: int) -> bytes:
        return self.data[self.start[i] : self.end[i]].tobytes()


def text_slices(column: pa.Array | pa.ChunkedArray) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """``(first row, bytes, offsets)`` of slices of a string column; a null counts as an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    array = pc.fill_null(column.cast(pa.large_string()), "")
    if isinstance(array, pa.ChunkedArray):
        array = array.combine_chunks()
    if not len(array):
        return
    offsets = np.frombuffer(array.buffers()[1], np.int64)[array.offset : array.offset + len(array) + 1]
    data = np.frombuffer(array.buffers()[2] or b"", np.uint8)
    i = 0
    while i < len(array):
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + SLICE, "right")) - 1)
        yield i, data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
        i = j
    relax()


def word_slices(column: pa.Array | pa.ChunkedArray, lower: bool = False) -> Iterator[Slice]:
    """Words ``[^\\x20\\x09-\\x0D]+`` of every text, optionally with A-Z lower-cased."""
    for first, data, offsets in text_slices(column):
        data = _LOWER[data] if lower else data
        inside = ~_SPACE[data]
        begin, finish = inside.copy(), inside.copy()
        begin[1:] &= ~inside[:-1]
        finish[:-1] &= ~inside[1:]
        cuts = offsets[1:-1]
        cuts = cuts[(cuts > 0) & (cuts < len(data))]
        begin[cuts] = inside[cuts]
        finish[cuts - 1] = inside[cuts - 1]
        start, end = np.flatnonzero(begin), np.flatnonzero(finish) + 1
        yield Slice(first, len(offsets) - 1, data, offsets, start, end, np.searchsorted(start, offsets))


def hash_spans(data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each span of bytes, eight bytes a step."""
    padded = np.concatenate([data, np.zeros(8, np.uint8)])
    eight = np.ndarray((len(padded) - 7,), "<u8", padded, strides=(1,))
    length = end - start
    h = mix(length.astype(np.uint64) * _M1 + _M1)
    live, at, left = None, start, length
    big = length > LONG_WORD
    if big.any():
        live = np.flatnonzero(~big)
        at, left = start[live], length[live]
    while len(at):
        part = eight[at] & _MASK[np.minimum(left, 8)]
        if live is None:
            h = mix(h ^ part * _M1)
        else:
            h[live] = mix(h[live] ^ part * _M1)
        more = np.flatnonzero(left > 8)
        live = more if live is None else live[more]
        at, left = at[more] + 8, left[more] - 8
    for i in np.flatnonzero(big):
        h[i] = int.from_bytes(hashlib.blake2b(data[start[i] : end[i]].tobytes(), digest_size=8).digest(), "little")
    return h


_POW: dict[str, np.ndarray] = {}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_POW.get("p", ())) < n:
        size = 1 << (n - 1).bit_length()
        base = 0x5851F42D4C957F2D
        for name, b in (("p", base), ("q", pow(base, -1, 1 << 64))):
            x = np.full(size, b, np.uint64)
            x[0] = 1
            _POW[name] = np.multiply.accumulate(x)
    return _POW["p"], _POW["q"]


def window_hashes(words: np.ndarray, width: int) -> np.ndarray:
    """A hash of every ``width`` consecutive values; position ``i`` covers ``words[i:i+width]``."""
    n = len(words) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    p, q = _powers(len(words) + 1)
    total = np.zeros(len(words) + 1, np.uint64)
    np.cumsum(words * p[: len(words)], out=total[1:])
    return mix((total[width:] - total[:n]) * q[:n])


def combine(parts: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """An order-free 64-bit hash of each run of ``parts`` that begins at ``starts``."""
    return mix(np.add.reduceat(mix(parts ^ _M1), starts)) if len(starts) else np.zeros(0, np.uint64)
